"""Chat formatting, mixing, quality rules, licence scans: SQL on given tables, and odd inputs."""

import hashlib
import re
import textwrap

import pytest
from pyspark.sql import functions as F

from gnnspark.llm import chat, licenses, mixing, quality, registry

ORACLES = registry.oracle_sql()


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_against_sql(spark, sf, duck, same, name):
    same(registry.queries()[name](spark, sf), duck.sql(ORACLES[name]))


def conversations(spark, rows):
    return spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, formatted string")


def test_chat_round_trip_and_automaton(spark):
    nasty = ["\\### Assistant: </turn> ok", "", None, "\\\\h\\l<#>\n", "</turn>\n### user\n", "é😀 " * 50]
    rows = [(1, i, "user" if i % 2 == 0 else "assistant", t, "clash") for i, t in enumerate(nasty)]
    rows += [(2, 0, "assistant", "first", None), (3, 0, None, "who", None), (3, None, "a\nb#<\\", "x", None), (None, 0, "user", "q", None), (4, 0, "user", "q", None), (4, 0, "user", "q", None)]
    out = chat.format_chats(conversations(spark, rows))
    told = {r["conv_id"]: r for r in out.withColumn("turns", chat.read_turns(F.col("formatted"))).withColumn("loss", chat.read_loss(F.col("segments"))).collect()}
    assert [t["text"] for t in told[1]["turns"]] == [t or "" for t in nasty]
    assert told[1]["valid"] and told[1]["loss"] == "".join((nasty[i] or "") for i in (1, 3, 5))
    assert not told[2]["valid"] and told[2]["bad_turn"] == 0 and told[2]["loss"] == "first"
    assert [(t["role"], t["text"]) for t in told[3]["turns"]] == [("a\nb#<\\", "x"), ("", "who")]
    assert told[None]["n_turns"] == 1 and not told[None]["valid"] and told[4]["n_turns"] == 2 and told[4]["bad_turn"] == 1
    d = {r["conv_id"]: r for r in chat.chat_digests(out).collect()}
    assert d[1]["turns_sha256"] == hashlib.sha256("".join(f"{'user' if i % 2 == 0 else 'assistant'}\n{t or ''}\n" for i, t in enumerate(nasty)).encode()).hexdigest()
    assert chat.format_chats(conversations(spark, [])).count() == 0


def test_template_must_be_escapable():
    with pytest.raises(ValueError):
        chat.ChatTemplate(opens=">> ", closes="<|end|>\n")


def docs_of(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, source string, size long, host string")


def test_mixing_targets_and_edges(spark):
    rows = [(i, "w " * (1 + i % 7), "a", 0, None) for i in range(400)] + [(1000 + i, "x y z", "b", 0, None) for i in range(40)] + [(2000 + i, "q", None, 0, None) for i in range(30)]
    rows += [(5000, None, "b", 0, None), (None, "n n", "b", 0, None), (1001, "x y z", "b", 0, None), (9, "", "empty", 0, None)]
    got = mixing.mix(docs_of(spark, rows)).collect()
    assert len(got) == len(rows)
    by = {}
    for r in got:
        size = 0 if r["size"] is None else r["size"]
        assert 0 <= r["taken"] <= 3 * size
        by.setdefault((r["target"], r["source_size"]), []).append(r["taken"])
    for (target, size), taken in by.items():
        assert target <= 3 * size and abs(sum(taken) - target) <= 4
    assert sum(t for t, _ in by) == pytest.approx(sum(s for _, s in by))
    again = mixing.mix(docs_of(spark, rows)).collect()
    assert sorted(map(str, got)) == sorted(map(str, again))
    assert mixing.mix(docs_of(spark, [])).count() == 0
    taken = mixing.take_mix(docs_of(spark, rows))
    assert taken.columns == ["doc_id", "text", "source", "size", "host"] and taken.count() > 0


def brute_repeats(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    from collections import Counter

    grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    c, hit = Counter(grams), set()
    for i, g in enumerate(grams):
        if c[g] > 1:
            hit |= {i, i + 1, i + 2}
    return len(hit)


def test_quality_counts(spark):
    texts = [None, "", " \n\t ", "a b", "a b c a b c a b c", "x\nx\n\nx y\nx y", "a a a a", "p q r s p q r t\x0bu", "# $% <|> word joined", "one two three " * 500]
    rows = [(i, t, "h" if i % 2 else None, 0, "clash") for i, t in enumerate(texts)]
    got = {r["doc_id"]: r for r in quality.judge(docs_of(spark, rows)).collect()}
    for i, t in enumerate(texts):
        t = t or ""
        words = re.findall(r"[^\x20\x09-\x0D]+", t)
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), brute_repeats(t)), i
        assert r["base_failed"] == (len(words) < 50 or 100 * brute_repeats(t) > 50 * len(words)) and not (r["kept"] and r["base_failed"])
    assert quality.judge(docs_of(spark, [])).count() == 0


def test_quality_host_rule(spark):
    """A bad host loses its soft failures but keeps its clean documents; a good host keeps both."""
    clean = " ".join(f"word{i}" for i in range(80))
    soft = " ".join(f"w{i}##" for i in range(80))
    rows = [(i, soft if i < 90 else clean, "bad", 0, None) for i in range(100)] + [(1000 + i, soft if i == 0 else clean, "good", 0, None) for i in range(100)]
    got = {r["doc_id"]: r["kept"] for r in quality.judge(docs_of(spark, rows)).collect()}
    assert not got[0] and got[95] and got[1000] and got[1001]


def test_quality_verdict_changes_rows(spark):
    """On the given documents some host lies above the fitted bound, and what it loses are documents that fail a soft rule only."""
    got = quality.judge(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).collect()
    lost = [r for r in got if not r["kept"] and not r["base_failed"]]
    assert lost and all(r["soft_failed"] and r["host_flagged"] for r in lost) and len(lost) < 0.05 * len(got)


def test_license_rules(spark):
    mit = " ".join(s for k, s in licenses.SENTENCES if k in ("mit_grant", "mit_notice", "as_is"))
    texts = [None, "", "no such thing", "Intro here. Released under the MIT License. More", "x\nLicensed under the Apache License, Version 2.0.\ny", mit, "Licensed under CC BY-NC 4.0.\nReleased under the MIT License.\nReleased under the MIT license.", "a license is mentioned"]
    got = {r["doc_id"]: r for r in licenses.scan(docs_of(spark, [(i, t, None, 0, None) for i, t in enumerate(texts)])).collect()}
    assert [got[i]["licenses"] for i in range(8)] == ["", "", "", "MIT", "Apache-2.0", "MIT", "MIT,CC-BY-NC-4.0", ""]
    assert got[5]["sentence_ids"] == "mit_grant,mit_notice,as_is" and got[5]["n_licenses"] == 1 and got[6]["n_licenses"] == 3
    assert licenses.scan(docs_of(spark, [])).count() == 0


def test_every_sentence_and_rule_is_met(spark):
    """Each listed sentence yields its identifier and each rule its licence, on one line and wrapped at 72 columns, behind comment marks or not."""
    whole = [(s, k, None) for k, s in licenses.SENTENCES]
    whole += [(" ".join(dict(licenses.SENTENCES)[k].rstrip(".:") + "." for k in seq), ",".join(seq), name) for name, seq in licenses.RULES]
    cases = [(make(t), ids, name) for t, ids, name in whole for make in (str, lambda t: textwrap.fill(t, 72), lambda t: "x\n" + textwrap.fill(t, 72, initial_indent=" * ", subsequent_indent=" * ") + "\ny")]
    got = {r["doc_id"]: r for r in licenses.scan(docs_of(spark, [(i, t, None, 0, None) for i, (t, _, _) in enumerate(cases)])).collect()}
    assert [got[i]["sentence_ids"] for i in range(len(cases))] == [ids for _, ids, _ in cases]
    assert all(name in (None, got[i]["licenses"]) for i, (_, _, name) in enumerate(cases))
