"""The corpus pipeline: each stage against a brute-force version on a small corpus, and odd inputs."""

import random
import re

from pyspark.sql import functions as F

import corpus_pipeline
from gnnspark.llm import pii, simhash

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def corpus(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def test_run_and_columns(spark, sf):
    out = corpus_pipeline.run(spark, sf)
    assert out.count() > 0 and {"doc_id", "n_tokens", "ids_sha256", "decoded_sha256"} <= set(out.columns)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language", "near_duplicates", "personal_data", "mixture", "tokens"]


def test_language_keeps_what_has_letters(spark, sf):
    docs = corpus(spark, sf)
    odd = spark.createDataFrame([(10**6, None, None, None, None), (10**6 + 1, "12 34 !!", "en", "s", 8), (10**6 + 2, "", "en", "s", 0)], SCHEMA)
    kept = {r[0] for r in corpus_pipeline.language(spark, docs.union(odd), sf).select("doc_id").collect()}
    assert kept == {r["doc_id"] for r in docs.collect() if any(c.isalpha() for c in r["text"])}


def least_of_groups(texts):
    """For each text the first text of its component at a five-word Jaccard similarity of 0.8, by comparing all pairs."""
    words = [re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), t or "")) for t in texts]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in words]
    root = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if root[i] != root[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                a, b = sorted((root[i], root[j]))
                root = [a if r == b else r for r in root]
    return root


def test_one_of_each_group(spark, sf):
    docs = corpus(spark, sf)
    twice = docs.union(docs.withColumn("doc_id", F.col("doc_id") + 10**6))
    kept = {r[0] for r in corpus_pipeline.near_duplicates(spark, twice, sf).select("doc_id").collect()}
    rows = sorted(docs.select("doc_id", "text").collect())
    assert kept == {rows[i]["doc_id"] for i in set(least_of_groups([r["text"] for r in rows]))}


def test_no_strict_span_is_left(spark, sf):
    docs = corpus(spark, sf).union(spark.createDataFrame([(10**6, None, None, None, None), (10**6 + 1, "a@b.co 1.2.3.4", "en", "s", 14)], SCHEMA))
    out = corpus_pipeline.personal_data(spark, docs, sf)
    assert out.columns == docs.columns and out.count() == docs.count()
    assert all(not pii.strict_spans(r["text"]) for r in out.collect())


def test_tokens_equal_the_library(spark, sf):
    """Ids and decoded text of every row against the tokenizers library."""
    import hashlib

    import tokenizers

    from gnnspark.llm.registry import tokenizer_path

    library = tokenizers.Tokenizer.from_file(tokenizer_path())
    docs = corpus(spark, sf).limit(60).union(spark.createDataFrame([(10**6, None, None, None, None), (10**6 + 1, "", "en", "s", 0)], SCHEMA))
    texts = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    for r in corpus_pipeline.tokens(spark, docs, sf).collect():
        ids = library.encode(texts[r["doc_id"]], add_special_tokens=False).ids
        said = library.decode(ids, skip_special_tokens=False)
        assert r["n_tokens"] == len(ids) and r["decoded_sha256"] == hashlib.sha256(said.encode()).hexdigest()
        assert r["ids_sha256"] == hashlib.sha256(b"".join(i.to_bytes(4, "little") for i in ids)).hexdigest()


def test_mixture_columns(spark, sf):
    docs = corpus(spark, sf)
    out = corpus_pipeline.mixture(spark, docs, sf)
    assert out.columns == docs.columns and 0 < out.count() <= 3 * docs.count()


def test_empty_tables(spark, sf):
    none = corpus(spark, sf).where("doc_id < 0")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, none, sf).count() == 0


def test_near_copies_by_five_word_jaccard(spark, sf):
    """Near copies at a similarity of 0.8 or more go even if their fingerprints are far apart, others stay; the rest agrees with brute force."""
    rng = random.Random(3)
    texts = []
    for share in (0, 1, 3, 6, 9, 14):
        for _ in range(4):
            base = [f"w{rng.randrange(3000)}" for _ in range(150)]
            near = list(base)
            for at in rng.sample(range(150), share):
                near[at] = f"z{rng.randrange(99)}"
            texts += [" ".join(base), " ".join(near).upper()]
    texts += [None, " ", "", "a b", "A  b", "a b c"] + ["same long run of words " * 30 + f"tail {i}" for i in range(40)]
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in ((t or "").lower().split() for t in texts)]
    root = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
                a, b = sorted((root[i], root[j]))
                root = [a if r == b else r for r in root]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], SCHEMA)
    kept = sorted(r["doc_id"] for r in corpus_pipeline.near_duplicates(spark, docs, sf).collect())
    assert kept == sorted(set(root))
    by_fingerprint = {r["doc_id"] for r in simhash.keep_one(docs).collect()}
    assert any(i in by_fingerprint and i + 1 in by_fingerprint and root[i] == root[i + 1] for i in range(0, 48, 2))


def test_language_fills_null_and_keeps_unlabelled(spark, sf):
    """A null lang takes the prediction; where no row has a label, documents with letters stay."""
    docs = corpus(spark, sf)
    hidden = docs.withColumn("lang", F.when(F.col("doc_id") % 3 > 0, F.col("lang")))
    got = {r["doc_id"]: r["lang"] for r in corpus_pipeline.language(spark, hidden, sf).collect()}
    true = {r["doc_id"]: r["lang"] for r in docs.collect()}
    filled = [i for i in got if i % 3 == 0]
    assert filled and all(got[i] for i in filled) and all(got[i] == true[i] for i in got if i % 3)
    assert sum(got[i] == true[i] for i in filled) >= 0.9 * len(filled)
    none = corpus_pipeline.language(spark, docs.withColumn("lang", F.lit(None).cast("string")), sf)
    assert {r["doc_id"] for r in none.collect()} == set(got) and none.where("lang is not null").count() == 0


def test_rows_not_ids_are_chosen(spark, sf):
    """A repeated id loses no text that is not linked; rows with a null id are compared like others."""
    a, b = "alpha beta gamma delta epsilon zeta", "one two three four five six seven"
    rows = [(1, a, "en"), (1, b, "en"), (1, a, "en"), (2, b, "en"), (None, b.upper(), "en"), (None, "solo text here", "en"), (None, "solo text here", "en"), (0, a, "en"), (3, None, "en")]
    docs = spark.createDataFrame([(*r, "s", 0) for r in rows], SCHEMA)
    got = sorted(((r["doc_id"], r["text"]) for r in corpus_pipeline.near_duplicates(spark, docs, sf).collect()), key=repr)
    assert got == sorted([(0, a), (1, b), (None, "solo text here"), (3, None)], key=repr)


def test_near_copies_take_part_in_fingerprint_links(spark):
    """The stage's SimHash step links all pairs of texts at two or fewer differing bits, equal fingerprints of different texts included."""
    from gnnspark.llm import neardup

    rng = random.Random(5)
    texts = [f"{i} " + " ".join(f"w{rng.randrange(5)}" for _ in range(3)) for i in range(20)]
    for i in range(12):
        base = [f"w{rng.randrange(3000)}" for _ in range(400)]
        texts += [" ".join(base), " ".join([*base, f"end{i}"]), "  ".join(base)]
    docs = spark.createDataFrame([(i, t, "en", "s", 0) for i, t in enumerate(texts)], SCHEMA)
    found = neardup.sketches(docs).cache()
    fp = {r["node"]: r["fp"] & (2**64 - 1) for r in found.collect()}
    assert set(fp.values()) == {int.from_bytes(simhash.fingerprint(t, 5), "big") for t in texts}
    root = {n: n for n in fp}
    for link in neardup.close_fingerprints(found).collect():
        a, b = root[link["src"]], root[link["dst"]]
        root = {n: a if r == b else r for n, r in root.items()}
    near = [(a, b) for a in fp for b in fp if a < b and (fp[a] ^ fp[b]).bit_count() <= 2]
    assert len(near) > 3 and all(root[a] == root[b] for a, b in near)


def test_few_edges_are_merged_without_rounds(spark, monkeypatch):
    """A small edge table needs no shuffle, and one task gives the labels of the rounds."""
    from gnnspark.llm import components

    rng = random.Random(2)
    pairs = [(i, i + 1) for i in range(100, 160)] + [(rng.randrange(-400, 400), rng.randrange(-400, 400)) for _ in range(300)] + [(7, 7), (None, 3), (3, 4), (4, 3)]
    edges = spark.createDataFrame(pairs, "src long, dst long")
    one = components.connected_components(edges)
    assert "Exchange" not in one._jdf.queryExecution().executedPlan().toString()
    assert components.connected_components(edges.where("src > 999")).count() == 0
    monkeypatch.setattr(components, "ONE_TASK", 0)
    assert sorted(one.collect()) == sorted(components.connected_components(edges).collect())
