"""Quality rules: counts per document, rule failures per host, shrunken host rates, verdicts joined back.

Only DataFrame functions are used. Counting works inside each row: three-word windows are sorted with their positions, equal
neighbours are repeats, and the positions they cover are summed; nothing is exploded or shuffled. The narrow table of counts is checkpointed, aggregated by host, and
joined with the hosts' verdicts.

A host's failure rate is shrunk towards the corpus by a beta prior fitted to the hosts by moments, so a host with few documents
is not condemned by one failure; a host is flagged when its shrunk rate lies more than ``host_z`` deviations above the mean of all hosts' shrunk rates, or above ``host_rate``. A document falls by a base rule, or by a soft rule when its host is flagged: clean documents of a
bad host stay.

Defined results: null text has no words (and so fails the base rule); a null host is a host of its own; repeated rows each get
a result; an empty table gives no rows. Only the named columns are read.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .state import checkpointed, let

SPACES = " \t\n\x0b\f\r"
SYMBOLS = "#*$%&|<>"


@dataclass(frozen=True)
class QualityRules:
    least_words: int = 50
    most_repeat_percent: int = 50
    most_symbols_per_100_words: int = 10
    most_dup_line_percent: int = 30
    least_word_chars: int = 2
    most_word_chars: int = 14
    host_rate: float = 0.5
    host_z: float = 1.0


def words_of(text: Column) -> Column:
    return F.filter(F.split(text, r"[\x20\x09-\x0D]+", -1), lambda w: w != "")


def repeat_words(words: Column) -> Column:
    """How many words lie in three-word windows that are found twice or more; exact, n log n in the words.

    Hashes of windows are sorted with their positions; only windows whose hash is found twice are compared as text.
    """
    none = F.array().cast("array<int>")

    def among(ws: Column) -> Column:
        hashed = lambda i: F.struct(F.xxhash64(F.get(ws, i), F.get(ws, i + 1), F.get(ws, i + 2)).alias("w"), i.alias("at"))
        every = F.when(F.size(ws) >= 3, F.transform(F.sequence(F.lit(0), F.size(ws) - 3), hashed)).otherwise(F.array().cast("array<struct<w:bigint,at:int>>"))
        said = lambda i: F.struct(F.concat_ws(" ", F.get(ws, i), F.get(ws, i + 1), F.get(ws, i + 2)).alias("w"), i.alias("at"))
        return let(let(F.sort_array(every), doubled), lambda at: F.when(F.size(at) > 0, F.sort_array(let(F.sort_array(F.transform(at, said)), doubled))).otherwise(none))

    def doubled(rows: Column) -> Column:
        same = lambda row, i: F.coalesce(F.get(rows, i)["w"] == row["w"], F.lit(False))
        return F.transform(F.filter(rows, lambda row, i: F.when(i > 0, same(row, i - 1)).otherwise(False) | same(row, i + 1)), lambda row: row["at"])

    begin = F.struct(F.lit(-3).alias("last"), F.lit(0).cast("long").alias("n"))
    covered = lambda acc, at: F.struct(at.alias("last"), (acc["n"] + F.least(F.lit(3), at - acc["last"])).alias("n"))
    return F.aggregate(let(words, among), begin, covered, lambda acc: acc["n"])


def measure(docs: DataFrame, id_col: str = "doc_id", text: str = "text", host: str = "source") -> DataFrame:
    """(doc_id, host, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words)."""
    whole = F.coalesce(F.col(text), F.lit(""))
    lines = F.filter(F.split(whole, "\n", -1), lambda line: F.translate(line, SPACES, "") != "")
    counts = let(lines, lambda ls: F.struct(F.size(ls).cast("long").alias("n"), (F.size(ls) - F.size(F.array_distinct(ls))).cast("long").alias("dup")))
    by_word = let(words_of(whole), lambda ws: F.struct(F.size(ws).cast("long").alias("n"), repeat_words(ws).alias("repeated")))
    told = docs.select(
        F.col(id_col).alias("doc_id"),
        F.col(host).alias("host"),
        by_word.alias("w"),
        counts.alias("l"),
        F.length(F.translate(whole, SPACES, "")).cast("long").alias("word_chars"),
        (F.length(whole) - F.length(F.translate(whole, SYMBOLS, ""))).cast("long").alias("n_symbols"),
    )
    return told.select("doc_id", "host", F.col("w.n").alias("n_words"), "word_chars", "n_symbols", F.col("l.n").alias("n_lines"), F.col("l.dup").alias("n_dup_lines"), F.col("w.repeated").alias("n_repeat_words"))


def failures(rules: QualityRules) -> tuple[Column, Column]:
    """(base rule failed, soft rule failed) over the columns of :func:`measure`; whole numbers only."""
    n = F.col("n_words")
    base = (n < rules.least_words) | (100 * F.col("n_repeat_words") > rules.most_repeat_percent * n)
    soft = (
        (100 * F.col("n_symbols") > rules.most_symbols_per_100_words * n)
        | (100 * F.col("n_dup_lines") > rules.most_dup_line_percent * F.col("n_lines"))
        | (F.col("word_chars") < rules.least_word_chars * n)
        | (F.col("word_chars") > rules.most_word_chars * n)
    )
    return base, soft


def host_verdicts(judged: DataFrame, rules: QualityRules) -> DataFrame:
    """(host, host_docs, host_rate, host_flagged) from rows (host, base_failed, soft_failed)."""
    bad = F.col("base_failed") | F.col("soft_failed")
    hosts = checkpointed(judged.groupBy("host").agg(F.count("*").alias("host_docs"), F.sum(bad.cast("long")).alias("host_bad")))
    rate = F.col("host_bad") / F.col("host_docs")
    m, v = hosts.agg(F.avg(rate), F.var_pop(rate)).first()
    m, strength = fitted_prior(m or 0.0, v or 0.0)
    shrunk = (F.col("host_bad") + m * strength) / (F.col("host_docs") + strength)
    centre, spread = hosts.agg(F.avg(shrunk), F.stddev_pop(shrunk)).first()
    bound = min(rules.host_rate, (centre or 0.0) + rules.host_z * (spread or 0.0) + 1e-9)
    return hosts.select("host", "host_docs", shrunk.alias("host_rate"), (shrunk > bound).alias("host_flagged"))


def fitted_prior(m: float, v: float) -> tuple[float, float]:
    """(mean, strength) of the beta prior with the hosts' mean and variance; hosts that do not differ have a prior of great strength."""
    return m, max(m * (1 - m) / v - 1, 1e-3) if v > 1e-9 and 0 < m < 1 else 1e6


def judge(docs: DataFrame, rules: QualityRules = QualityRules(), id_col: str = "doc_id", text: str = "text", host: str = "source") -> DataFrame:
    """The columns of :func:`measure` with base_failed, soft_failed, host_rate, host_flagged and kept."""
    base, soft = failures(rules)
    judged = checkpointed(measure(docs, id_col, text, host).withColumns({"base_failed": base, "soft_failed": soft}))
    hosts = host_verdicts(judged, rules).withColumnRenamed("host", "h")
    joined = judged.join(hosts, judged["host"].eqNullSafe(hosts["h"])).drop("h")
    return joined.withColumn("kept", ~F.col("base_failed") & ~(F.col("host_flagged") & F.col("soft_failed")))
