"""Language, BPE, PII, SimHash, WARC, embeddings, components: brute force, round trips, held-out accuracy, odd inputs."""

import base64
import hashlib
import json
import random
import re

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from gnnspark.llm import bpe, components, embeddings, langid, pii, registry, simhash, warc

ODD = [None, "", " ", "\n\n", "1234 5678", "ok", "é" * 3000, "a b " * 20000]


def docs_of(spark, texts, start=0):
    return spark.createDataFrame([(start + i, t, "en", "s", 0, 1, 0.5) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long, fp long, score double")


def components_of(n, links):
    root = list(range(n))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return [find(i) for i in range(n)]


# ---- components ----


def test_components_match_union_find(spark):
    r = random.Random(1)
    links = [(r.randrange(300), r.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(100, 160)]
    got = {x["node"]: x["component"] for x in components.connected_components(spark.createDataFrame(links, "src long, dst long")).collect()}
    want = components_of(300, links)
    assert all(got.get(i, i) == want[i] for i in range(300))
    assert components.connected_components(spark.createDataFrame([], "src long, dst long")).count() == 0


# ---- language ----


def test_language_held_out(spark, sf):
    rows = registry.op2_langid(spark, sf).join(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r["lang_pred"] == r["lang"] for r in rows) / len(rows) > 0.93 and all(0 <= r["score"] <= 1 for r in rows)


def test_language_odd_inputs(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = langid.train(docs, per_label=200)
    got = [r for r in langid.identify(docs_of(spark, ODD), model).orderBy("doc_id").collect()]
    assert [r["lang_pred"] == "und" for r in got] == [True, True, True, True, True, False, False, False]
    empty = langid.train(docs.where("lang = 'none'"))
    assert langid.identify(docs_of(spark, ["hello"]), empty).first()["lang_pred"] == "und"
    assert langid.identify(docs_of(spark, ODD).where("doc_id < 0"), model).count() == 0


def test_network_gradients():
    net = langid.ByteCnn(["a", "b", "c"], 16, filters=3, dim=2)
    net.start(3)
    net.params = {k: v.astype(np.float64) for k, v in net.params.items()}
    rng = np.random.default_rng(0)
    x, y = rng.integers(97, 105, (5, 16)).astype(np.uint8), np.array([0, 1, 2, 1, 0])
    loss = lambda: -net.log_probs(x)[np.arange(5), y].mean()
    grads = net.gradients(x, y)
    for k, at in (("w2", (1, 2)), ("w3", (4, 0)), ("b4", (1,)), ("o", (5, 1)), ("c", (2,)), ("e", (100, 1))):
        old = net.params[k][at]
        net.params[k][at] = old + 1e-5
        up = loss()
        net.params[k][at] = old - 1e-5
        down = loss()
        net.params[k][at] = old
        assert grads[k][at] == pytest.approx((up - down) / 2e-5, abs=1e-4), k


# ---- BPE ----


@pytest.fixture(scope="module")
def both():
    from tokenizers import Tokenizer

    path = registry.tokenizer_path()
    with open(path, encoding="utf-8") as f:
        return bpe.Bpe(f.read()), Tokenizer.from_file(path)


def test_bpe_equals_library(both):
    mine, theirs = both
    r = random.Random(5)
    alphabet = [chr(c) for c in [*range(0x180), 0x2028, 0x3000, 0x180E, 0x1F600, 0x4E00, 0x0E01, 0x661, 0x2167]] + [" ", "\n", "'s", "<|endoftext|>", "the", "ing"] * 20
    texts = ["".join(r.choice(alphabet) for _ in range(r.randint(0, 80))) for _ in range(1500)] + ["ab" * 3000 + "x" * 1000, "", " " * 300, "\n" * 50 + "a"]
    for t, ids in zip(texts, mine.encode_many(texts)):
        want = theirs.encode(t, add_special_tokens=False).ids
        assert ids.tolist() == want and mine.decode(want) == theirs.decode(want, skip_special_tokens=False)


def test_bpe_long_text_in_pieces(both, monkeypatch):
    mine, theirs = both
    monkeypatch.setattr(bpe, "CHARS_AT_ONCE", 500)
    monkeypatch.setattr(bpe, "WORDS_AT_ONCE", 37)
    monkeypatch.setattr(bpe, "REMEMBERED", 50)
    text = ("The quick brown fox, naïve <|endoftext|> café 123.  \n" * 60) + "end"
    assert mine.encode(text).tolist() == theirs.encode(text, add_special_tokens=False).ids


@pytest.mark.parametrize("change, named", [
    ({"normalizer": {"type": "Lowercase"}}, "normalizer"), ({"pre_tokenizer": {"type": "Whitespace"}}, "pre_tokenizer"),
    ({"pre_tokenizer": {"type": "ByteLevel", "add_prefix_space": True}}, "pre_tokenizer"), ({"decoder": None}, "decoder"),
    ({"added_tokens": [{"id": 3, "content": "<x>", "lstrip": True}]}, "added_tokens"),
    ({"model": {"type": "WordPiece", "vocab": {}, "merges": []}}, "model type"), ({"model": {"type": "BPE", "dropout": 0.1, "vocab": {}, "merges": []}}, "dropout"),
])
def test_bpe_refuses_what_it_does_not_do(change, named):
    plain = {"normalizer": None, "pre_tokenizer": {"type": "ByteLevel", "add_prefix_space": False}, "decoder": {"type": "ByteLevel"}, "added_tokens": [], "model": {"type": "BPE", "vocab": {}, "merges": []}}
    assert not bpe.refused(plain)
    with pytest.raises(ValueError, match=named):
        bpe.Bpe(json.dumps(plain | change))


def test_bpe_tables(spark, both):
    path = registry.tokenizer_path()
    docs = docs_of(spark, ODD)
    back = bpe.decode(bpe.encode(docs, path), path).orderBy("doc_id").collect()
    assert [r["decoded"] for r in back] == [t or "" for t in ODD]
    told = bpe.digests(docs, path).orderBy("doc_id").collect()
    assert [r["decoded_sha256"] for r in told] == [hashlib.sha256((t or "").encode()).hexdigest() for t in ODD]
    assert told[5]["ids_sha256"] == hashlib.sha256(np.array(both[1].encode("ok").ids, "<u4").tobytes()).hexdigest()
    assert bpe.digests(docs.where("doc_id < 0"), path).count() == 0


# ---- personal data ----

PLAIN = {
    "email": re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),
    "ip": re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    "card": re.compile(r"[0-9]([\x20-]?[0-9])+"),
    "phone": re.compile(r"\+[0-9][\x20().0-9-]+[0-9]"),
}


def plain_spans(text):
    out = []
    for kind, p in PLAIN.items():
        for m in p.finditer(text or ""):
            d = re.sub("[^0-9]", "", m.group())
            fits = {"email": True, "ip": all(int(x) <= 255 for x in m.group().split(".")) if kind == "ip" else None, "card": 16 <= len(d) <= 19 and pii.luhn(d), "phone": 8 <= len(d) <= 15}[kind]
            if fits:
                out.append((kind, m.start(), m.end()))
    return out


def test_pii_base_equals_plain_patterns():
    r = random.Random(2)
    parts = ["a@b.co", "x.y+z@host-1.example.org", "@", ".", "1.2.3.4", "256.1.1.1", "10.0.0.255.7", "4111 1111 1111 1111", "4111111111111112", "5500-0000-0000-0004", "+1 (262) 555-7240", "+12", "+", " ", "-", "é", "abc", "0", "99", "a@b", "@c.de", "00012.1.1.1", "+49 30 123456789012345", "1111 2222"]
    for _ in range(4000):
        t = "".join(r.choice(parts) + r.choice(["", "", " ", "."]) for _ in range(r.randint(0, 12)))
        assert pii.strict_spans(t) == plain_spans(t), t


def test_pii_linear_on_long_runs():
    for t in ("a" * 300_000, "1" * 300_000, "+" * 100_000, "a@" * 100_000, "1." * 100_000, "+1" + "." * 200_000):
        pii.strict_spans(t)


def test_pii_model_and_redaction(spark):
    texts = ["call me by phone (262) 555-7240 now", "mail: jo (at) example (dot) com please", "version 123-456-7890 of the release", "card 4111 1111 1111 1111", "x@y.org and +1 (262) 555-7240", "ip 10.1.2.3 host", None, "", "nothing here", "x@y.org 10.1.2.3"] * 20
    docs = docs_of(spark, texts)
    model = pii.train(docs)
    assert model.tables.shape == (2, 5, 3) and model.tables.sum(2) == pytest.approx(1)
    got = pii.find(docs, model).orderBy("doc_id").limit(10).collect()
    for r, t in zip(got, texts):
        base = plain_spans(t)
        assert r["base_sha256"] == hashlib.sha256(pii.told(base).encode()).hexdigest()
        assert all(f"{k}:{s}:{e}" in r["spans"] for k, s, e in base)
    out = pii.redact(docs, model).orderBy("doc_id").limit(10).collect()
    assert out[4]["text"] == "[EMAIL] and [PHONE]" and out[6]["text"] is None and out[8]["text"] == "nothing here"
    none = docs.where("doc_id < 0")
    assert pii.find(none, pii.train(none)).count() == 0


def slow_estimate(groups, vote, n, n_groups, rounds):
    """The same estimation, pattern by pattern."""
    k = len(vote[0])
    tables = [[[b / sum(pii.BELIEF[y]) for b in pii.BELIEF[y]] for _ in range(k)] for y in (0, 1)]
    priors = [0.5] * n_groups
    for _ in range(rounds):
        soft = []
        for g, v in zip(groups, vote):
            p = [1 - priors[g], priors[g]]
            for y in (0, 1):
                for i in range(k):
                    p[y] *= tables[y][i][v[i]]
            soft.append(p[1] / sum(p))
        priors = [(sum(m * s for m, s, h in zip(n, soft, groups) if h == g) + 1) / (sum(m for m, h in zip(n, groups) if h == g) + 2) for g in range(n_groups)]
        for y in (0, 1):
            for i in range(k):
                c = [sum(m * (s if y else 1 - s) for m, s, v in zip(n, soft, vote) if v[i] == x) + pii.BELIEF[y][x] for x in range(3)]
                tables[y][i] = [x / sum(c) for x in c]
    return priors, tables, soft


def test_pii_reliabilities_are_recovered():
    """Votes drawn from known priors and reliabilities give them back; a slow version agrees."""
    rng = np.random.default_rng(1)
    yes = np.array([[0.05, 0.15, 0.8], [0.1, 0.1, 0.8], [0.05, 0.45, 0.5], [0.02, 0.58, 0.4], [0.1, 0.8, 0.1]])
    no = np.array([[0.7, 0.2, 0.1], [0.5, 0.3, 0.2], [0.3, 0.6, 0.1], [0.1, 0.8, 0.1], [0.6, 0.3, 0.1]])
    drawn = []
    for g, prior in enumerate((0.15, 0.6)):
        for is_yes in rng.random(6000) < prior:
            drawn.append((g, *(int(rng.choice(3, p=t)) for t in (yes if is_yes else no))))
    counts = {}
    for d in drawn:
        counts[d] = counts.get(d, 0) + 1
    keys = sorted(counts)
    groups, vote, n = np.array([k[0] for k in keys]), np.array([k[1:] for k in keys]), np.array([counts[k] for k in keys], float)
    priors, tables, soft = pii.estimate(groups, vote, n, 2, 300)
    assert priors == pytest.approx([0.15, 0.6], abs=0.05) and np.abs(tables[1] - yes).max() < 0.08 and np.abs(tables[0] - no).max() < 0.08
    fast, slow = pii.estimate(groups, vote, n, 2, 5), slow_estimate(groups.tolist(), vote.tolist(), n.tolist(), 2, 5)
    for a, b in zip(fast, slow):
        assert np.allclose(a, np.array(b), atol=1e-9)


def test_pii_method_decides_on_given_texts(spark, sf):
    """Keys in quotes are added, digits that fail their check are not; no prior of a group with candidates is at its end."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    docs = docs.union(docs.limit(0)).select("doc_id", "text")
    extra = ["order 4111 1111 1111 1112 shipped", "see 1234567812345678 there", 'token = "04dbebab91ab85687d33eeaaf9ac699e1188f962" x', "call (262) 555-7240 by phone", "on 2024-01-15 or 12:30:45", "version 300.1.2.3"] * 30
    more = spark.createDataFrame([(10**6 + i, t) for i, t in enumerate(extra)], "doc_id long, text string")
    model = pii.train(docs.union(more))
    assert 0.01 < model.priors[2 * pii.KINDS.index("card")] < 0.5 < model.priors[2 * pii.KINDS.index("secret")]
    got = {r["doc_id"]: r["spans"] for r in pii.find(more, model).collect()}
    assert [got[10**6 + i] for i in range(6)] == ["", "", "secret:9:49", "phone:5:19", "", ""]


def test_pii_loose_spans_are_linear():
    for t in ("1 " * 200_000, "ab1" * 100_000, "1:" * 200_000, "(1)" * 100_000, "a1b2c3d4e5f6g7h8i9j0k1 " * 20_000):
        assert len(pii.loose_spans(t, [])) <= len(t)


# ---- SimHash ----


def plain_fingerprint(text):
    w = [x for x in re.split(rb"[\x20\x09-\x0D]+", (text or "").encode().lower()) if x]
    grams = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([b" ".join(w)] if w else [])
    hs = [xxhash.xxh64_intdigest(g, 42) for g in grams]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hs) * 2 > len(hs))


def variants(rng, n=60):
    base = " ".join(f"w{rng.randrange(5000)}" for _ in range(260)).split()
    out = [" ".join(base)] * 4
    for _ in range(n):
        w = list(base)
        for _ in range(rng.randint(0, 2)):
            w[rng.randrange(len(w))] = f"z{rng.randrange(9)}"
        out.append(" ".join(w))
    return out


def test_simhash_brute_force(spark):
    rng = random.Random(4)
    texts = variants(rng) + variants(rng) + [" ".join(f"v{rng.randrange(9999)}" for _ in range(50)) for _ in range(40)] + ODD[:6] + ["A  B\tc", "a b C"]
    fps = [plain_fingerprint(t) for t in texts]
    want = components_of(len(texts), [(i, j) for i in range(len(texts)) for j in range(i) if bin(fps[i] ^ fps[j]).count("1") <= 2])
    got = simhash.near_duplicates(docs_of(spark, texts)).orderBy("doc_id").collect()
    assert [r["fingerprint"] for r in got] == [f"{f:016x}" for f in fps]
    assert [r["component_id"] for r in got] == want
    kept = sorted(r["doc_id"] for r in simhash.keep_one(docs_of(spark, texts)).collect())
    assert kept == sorted(set(want))
    assert simhash.near_duplicates(docs_of(spark, [])).count() == 0


def test_simhash_large_bucket_in_blocks(spark, monkeypatch):
    """Fingerprints that share most blocks are compared in many small units, and none of their links is lost."""
    from gnnspark.llm import blockpairs

    rng = random.Random(9)
    fps = sorted({(7 << 40) | sum(1 << b for b in rng.sample(range(20), rng.randint(0, 4))) for _ in range(400)})
    want = components_of(len(fps), [(i, j) for i in range(len(fps)) for j in range(i) if bin(fps[i] ^ fps[j]).count("1") <= 2])
    keyed = spark.createDataFrame([(f,) for f in fps], "fp long")
    real = blockpairs.dealt
    monkeypatch.setattr(simhash, "dealt", lambda members, node: real(members, node, block=32))
    label = {r["node"]: r["component"] for r in components.connected_components(simhash.links(keyed)).collect()}
    assert [label.get(f, f) for f in fps] == [fps[w] for w in want]


def test_simhash_repeats_and_null_ids(spark):
    d = spark.createDataFrame([(1, "x y z w"), (1, "x y z w"), (None, "x y z w"), (0, None), (None, "q")], "doc_id long, text string")
    got = simhash.near_duplicates(d).collect()
    assert len(got) == 5 and {r["component_id"] for r in got if r["doc_id"] == 1} == {1}
    assert simhash.keep_one(d).count() == 4


# ---- WARC ----


def test_warc_round_trip(spark, sf, tmp_path):
    rows = [(1, "http://a/é b", "<p>x</p>"), (2, None, "<p>x</p>"), (3, "u", None), (4, "u", ""), (5, "u", "y" * 3_000_000), (6, "u", "é😀\r\n\r\nWARC/1.1"), (None, "u", "<p>x</p>"), (7, "u", "z"), (7, "u", "z")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    folder = f"file://{tmp_path}/w"
    manifest = warc.archive(pages, folder, bundle_bytes=1 << 20)
    got = warc.read_bundles(manifest, folder, payloads=True).collect()
    kinds = {(r["page_id"], r["record_type"], r["refers_to"]) for r in got}
    assert kinds == {(1, "revisit", 2), (2, "response", None), (3, "revisit", 4), (4, "response", None), (5, "response", None), (6, "response", None), (None, "response", None), (7, "response", None)} and len(got) == 9
    digest = lambda h: base64.b32encode(hashlib.sha1((h or "").encode()).digest()).decode()
    want = {i: h for i, _, h in rows}
    for r in got:
        h = want[r["page_id"]] or ""
        assert (r["payload_bytes"], r["payload_digest"]) == (len(h.encode()), digest(h))
        assert bytes(r["payload"]) == (b"" if r["record_type"] == "revisit" else h.encode())
    store, _ = warc.opened(folder)
    for m in manifest.collect():
        with store.open_input_file(m["path"]) as f:
            b = warc.Bundle(f)
            for key in b.index():
                assert b.record(key).record_id == key
    assert warc.archive(pages.where("page_id < 0"), f"file://{tmp_path}/none").count() == 0


# ---- embeddings ----


def test_embeddings_brute_force(spark):
    rng = np.random.default_rng(3)
    vectors, labels = [], []
    for c in range(12):
        centre = rng.standard_normal(16)
        for _ in range(20):
            vectors.append((centre + rng.standard_normal(16) * 0.1).astype(np.float32).tolist())
            labels.append(c % 3)
    vectors += [vectors[0]] * 30 + [(2 * np.array(vectors[0])).tolist(), [0.0] * 16, None, [float("nan")] * 16, [None] * 16, [1e30] * 16, vectors[0], vectors[1][:8], vectors[0]]
    labels += [labels[0]] * 30 + [labels[0], 0, 0, 0, 0, 0, None, 0, labels[0]]
    ok = [v is not None and l is not None and all(x is not None and np.isfinite(x) for x in v) and any(v) for v, l in zip(vectors, labels)]
    unit = [np.array(v, np.float32).astype(float) / np.linalg.norm(np.array(v, np.float32).astype(float)) if k else None for v, k in zip(vectors, ok)]
    links = [(i, j) for i in range(len(vectors)) for j in range(i) if ok[i] and ok[j] and labels[i] == labels[j] and len(unit[i]) == len(unit[j]) and unit[i] @ unit[j] >= 0.98]
    df = spark.createDataFrame([(i, v, l, 0) for i, (v, l) in enumerate(zip(vectors, labels))], "vec_id long, embedding array<float>, label int, node int")
    got = embeddings.near_duplicates(df, tables=24).orderBy("vec_id").collect()
    count = [0] * len(vectors)
    for a, b in links:
        count[a] += 1
        count[b] += 1
    found = sum(r["n_links"] for r in got)
    assert len(got) == len(vectors) and all(r["n_links"] <= c for r, c in zip(got, count)) and found >= 0.99 * sum(count)
    assert [r["component_id"] for r in got] == components_of(len(vectors), links)
    assert all(r["kept"] == (r["vec_id"] == r["component_id"]) for r in got)
    assert embeddings.near_duplicates(df.where("vec_id < 0")).count() == 0


def test_embeddings_counts_do_not_depend_on_blocks(spark, monkeypatch):
    from gnnspark.llm import blockpairs

    rng = np.random.default_rng(5)
    centre = rng.standard_normal(16)
    df = spark.createDataFrame([(i, (centre + rng.standard_normal(16) * 0.05).tolist(), 1) for i in range(150)], "vec_id long, embedding array<float>, label int")
    whole = embeddings.near_duplicates(df).orderBy("vec_id").collect()
    real = blockpairs.dealt
    monkeypatch.setattr(embeddings, "dealt", lambda members, node: real(members, node, block=16))
    assert embeddings.near_duplicates(df).orderBy("vec_id").collect() == whole


def test_embeddings_recall_at_shipped_parameters(spark):
    """Pairs planted at a cosine just above 0.98 are found by the defaults; those just below are no links."""
    rng = np.random.default_rng(5)
    rows, want = [], 0
    for i in range(1500):
        u = rng.standard_normal(64)
        u /= np.linalg.norm(u)
        w = rng.standard_normal(64)
        w -= (w @ u) * u
        w /= np.linalg.norm(w)
        c = 0.981 if i % 3 else 0.979
        want += c > 0.98
        rows += [(2 * i, u.tolist(), i % 2), (2 * i + 1, (c * u + (1 - c * c) ** 0.5 * w).tolist(), i % 2)]
    got = embeddings.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")).collect()
    linked = {r["vec_id"] for r in got if r["n_links"]}
    assert all(v // 2 % 3 for v in linked) and len(linked) // 2 >= 0.99 * want


def test_components_split_hubs(spark):
    """A star, chained to a path, is one component; with a low bound its centre is a hub in every round."""
    n = 3000
    edges = [(0, i) for i in range(1, n)] + [(n - 1, n), (n, n + 1), (n + 5, n + 6)]
    label = {r["node"]: r["component"] for r in components.connected_components(spark.createDataFrame(edges, "src long, dst long")).collect()}
    assert label == {i: 0 for i in range(n + 2)} | {n + 5: n + 5, n + 6: n + 5}
