"""Slow versions of operators that SQL cannot express, planted groups, and odd tables."""

import base64
import hashlib
import math

import pytest
from pyspark.sql import functions as F

from gnnspark.llm import bpe, langid, pii, quality, registry, simhash, warc


def slow_language(model, text):
    """One text by loops over windows, widths, filters and positions."""
    if text is None or not any(c.isalpha() for c in text):
        return "und", 0.0
    data = []
    for b in text.lower().encode("utf-8", "replace"):
        b = b if b >= 128 or 97 <= b <= 122 else b + 32 if 65 <= b <= 90 else 32
        if not (b == 32 and data and data[-1] == 32):
            data.append(b)
    p, sums, weight = model.params, [0.0] * len(model.labels), 0
    for at in range(0, len(data), model.window):
        piece = (data[at : at + model.window] + [32] * model.window)[: model.window]
        emb = p["e"][piece].astype(float)
        hidden = []
        for w in model.widths:
            for f in range(model.filters):
                kernel = p[f"w{w}"][:, f].astype(float)
                best = max(float(emb[i : i + w].ravel() @ kernel) for i in range(model.window - w + 1))
                hidden.append(max(best + float(p[f"b{w}"][f]), 0.0))
        z = [sum(h * float(o) for h, o in zip(hidden, p["o"][:, k])) + float(p["c"][k]) for k in range(len(model.labels))]
        top = max(z)
        log_sum = top + math.log(sum(math.exp(v - top) for v in z))
        share = sum(b != 32 for b in piece)
        weight += share
        sums = [s + share * (v - log_sum) for s, v in zip(sums, z)]
    mean = [s / max(weight, 1) for s in sums]
    top = max(mean)
    odds = [math.exp(v - top) for v in mean]
    return model.labels[mean.index(top)], max(odds) / sum(odds)


def test_language_predictions_equal_slow_ones(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    model = langid.train(docs, per_label=100)
    texts = [r["text"] for r in docs.orderBy("doc_id").select("text").head(12)] + ["A", "été 1999", "x" * 700, "123", None, "a  b\n\nc" * 90]
    table = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in langid.identify(table, model).collect()}
    for i, text in enumerate(texts):
        label, score = slow_language(model, text)
        assert got[i]["score"] == pytest.approx(score, abs=1e-3)
        assert got[i]["lang_pred"] == label


def test_language_learns_from_the_other_folds_only(spark):
    rows = [(i, f"{'abc def ghi' if i % 2 else 'xyz uvw rst'} {i}", "one" if i % 2 else "two") for i in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    held = langid.fold(F.col("doc_id")) == 1
    spoiled = docs.withColumn("lang", F.when(held, F.lit("wrong")).otherwise(F.col("lang")))
    assert langid.train(spoiled).labels == ["one", "two"]
    same = docs.withColumn("text", F.when(held, F.lit("zzz")).otherwise(F.col("text")))
    assert sorted(langid.sample(same, "doc_id", "text", "lang", 100, 64, 2)) == sorted(langid.sample(docs, "doc_id", "text", "lang", 100, 64, 2))


@pytest.mark.parametrize("bound", [10**6, 0])
def test_warc_large_group_of_equal_payloads(spark, tmp_path, monkeypatch, bound):
    """A third of all pages are one payload and some hundreds come in pairs; with and without a broadcast of the repeated digests."""
    monkeypatch.setattr(warc, "BROADCAST_ROWS", bound)
    html = lambda i: "hot" * 50 if i % 3 == 0 else f"pair {i // 6}" if i % 3 == 1 else f"page {i}"
    pages = spark.range(3000).select(F.col("id").alias("page_id"), F.lit("http://h/").alias("url"), F.when(F.col("id") % 3 == 0, F.repeat(F.lit("hot"), 50)).when(F.col("id") % 3 == 1, F.concat(F.lit("pair "), F.floor(F.col("id") / 6))).otherwise(F.concat(F.lit("page "), F.col("id"))).alias("html")).repartition(7, "page_id")
    folder = f"file://{tmp_path}/{bound}"
    got = {r["page_id"]: r for r in warc.read_bundles(warc.archive(pages, folder, bundle_bytes=1 << 14), folder).collect()}
    top = {}
    for i in range(3000):
        top[html(i)] = i
    assert len(got) == 3000
    for i, r in got.items():
        first = top[html(i)]
        assert (r["record_type"], r["refers_to"]) == (("response", None) if first == i else ("revisit", first))
        assert r["payload_digest"] == base64.b32encode(hashlib.sha1(html(i).encode()).digest()).decode()


def test_repeated_rows_and_clashing_columns(spark, sf):
    """Each of repeated rows has its result, and columns named like internal ones change nothing."""
    rows = [(1, "mail a@b.org or +49 30 1234567", "en", "s"), (1, "mail a@b.org or +49 30 1234567", "en", "s"), (None, None, None, None), (2, "ein Text ohne Daten", "de", "s"), (2, "other text", "en", None)]
    plain = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").withColumn("n_chars", F.length("text").cast("long"))
    clash = ["score", "lang_pred", "h", "label", "fp", "component", "host", "kind", "r", "n", "size", "k", "words", "spans"]
    odd = plain.withColumns({c: F.lit("x") for c in clash})
    model = langid.train(spark.read.parquet(f"{sf}/documents.parquet"), per_label=50)
    people = pii.train(plain)
    forms = {
        "language": lambda d: langid.identify(d, model),
        "tokens": lambda d: bpe.digests(d, registry.tokenizer_path(), keep=("doc_id", "lang")),
        "private": lambda d: pii.redact(d, people).select("doc_id", "text"),
        "sketch": lambda d: simhash.keep_one(d).select("doc_id", "text"),
    }
    for name, form in forms.items():
        a, b = (sorted(map(repr, (tuple(r) for r in form(d).collect()))) for d in (plain, odd))
        assert a == b, name
        assert len(a) == (5 if name != "sketch" else len(a)), name


def test_quality_repeated_and_null_ids(spark):
    text = "word " * 60
    docs = spark.createDataFrame([(1, "a b c", "s"), (1, "a b c", "s"), (None, text, None), (None, None, None)], "doc_id long, text string, source string")
    told = quality.judge(docs).collect()
    got = sorted(((r["doc_id"], r["n_words"], r["base_failed"]) for r in told), key=repr)
    assert got == sorted([(1, 3, True), (1, 3, True), (None, 60, True), (None, 0, True)], key=repr)
    assert not any(r["kept"] for r in told)
