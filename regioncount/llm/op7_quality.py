"""Quality rules as a short-circuit cascade, in DataFrame functions only.

A rule is a condition under which a document is rejected. On a sample the cost of each rule (characters and elements
that it reads) and its selectivity (share rejected) are estimated; rules then run in the order of rejections per cost,
each one only for the documents that all rules before it let through. Measures that the result holds are computed for
every document; rules that need more (lines' ends and starts, letters, distinct words) compute it inside the cascade,
where documents already rejected do not come. The verdict does not depend on the order, only the time does.

Defined cases: null text is the empty text, which has no words and fails; extra columns are ignored; repeated rows
are judged one by one; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Fixed values of the contract.
WHITE = " \t\n\x0b\x0c\r"
SYMBOLS = "#*$%&|<>"


def words(text: Column) -> Column:
    """Array of the ASCII-space separated words of a text."""
    inner = F.btrim(text, F.lit(WHITE))
    return F.when(inner == "", F.array().cast("array<string>")).otherwise(F.split(inner, "[\\x20\\x09-\\x0D]+"))


def word_chars(text: Column) -> Column:
    return F.char_length(F.translate(text, WHITE, ""))


def n_symbols(text: Column) -> Column:
    return F.char_length(text) - F.char_length(F.translate(text, SYMBOLS, ""))


def n_dup_lines(text: Column) -> Column:
    """Lines with a word that equal an earlier line."""
    full = full_lines(text)
    return F.size(full) - F.size(F.array_distinct(full))


def with_repeats(df: DataFrame, words_column: str, into: str) -> DataFrame:
    """Add the number of words inside 3-word windows that occur twice or more.

    Windows are hashed; sorted hashes show whether any repeats at all. Only then windows are sorted with their
    positions: neighbours with one hash are repeats, and the union of their words is counted from position gaps.
    """
    w = F.col(words_column)
    hashes = F.transform(F.sequence(F.lit(0), F.size(w) - 3), lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)))
    df = df.withColumn("__rc_h", F.when(F.size(w) >= 3, hashes).otherwise(F.array().cast("array<bigint>")))
    df = df.withColumn("__rc_any", F.size(F.array_distinct("__rc_h")) < F.size("__rc_h"))
    paired = F.transform("__rc_h", lambda h, i: F.struct(h.alias("h"), i.alias("i")))
    df = df.withColumn("__rc_s", F.when(F.col("__rc_any"), F.sort_array(paired)))
    s = F.col("__rc_s")
    twice = F.filter(s, lambda x, i: F.coalesce(F.get(s, i - 1)["h"] == x["h"], F.lit(False)) | F.coalesce(F.get(s, i + 1)["h"] == x["h"], F.lit(False)))
    df = df.withColumn("__rc_p", F.sort_array(F.transform(twice, lambda x: x["i"])))
    p = F.col("__rc_p")
    gaps = F.transform(p, lambda x, i: F.least(F.lit(3), F.coalesce(F.get(p, i + 1) - x, F.lit(3))))
    covered = F.aggregate(gaps, F.lit(0), lambda a, x: a + x)
    return df.withColumn(into, F.when(F.col("__rc_any"), covered).otherwise(F.lit(0))).drop("__rc_h", "__rc_any", "__rc_s", "__rc_p")


@dataclass(frozen=True)
class Rule:
    name: str
    #: True where the document is rejected.
    reject: Column
    #: Characters and elements read to decide; 1 where the result's measures suffice.
    work: Column


def full_lines(text: Column) -> Column:
    """Lines with a word."""
    return F.filter(F.split(text, "\n"), lambda x: F.btrim(x, F.lit(WHITE)) != "")


def rules() -> list[Rule]:
    """Production rules over the columns of `measures`."""
    c = F.col
    text, found = c("__rc_text"), c("__rc_words")
    one, whole = F.lit(1), F.char_length(text)
    ends = F.size(F.filter(full_lines(text), lambda x: x.rlike(r"(\.\.\.|\u2026)[\x20\x09-\x0D]*\z")))
    starts = F.size(F.filter(full_lines(text), lambda x: x.rlike("^[\\x20\\x09-\\x0D]*[-*\u2022]")))
    letters = F.size(F.filter(found, lambda x: x.rlike(r"[A-Za-z\x{80}-\x{10FFFF}]")))
    return [
        Rule("few_words", c("n_words") < 50, one),
        Rule("many_words", c("n_words") > 100_000, one),
        Rule("word_length", (c("word_chars") < 2 * c("n_words")) | (c("word_chars") > 15 * c("n_words")), one),
        Rule("symbols", c("n_symbols") * 10 > c("n_words"), one),
        Rule("dup_lines", c("n_dup_lines") * 100 > 30 * c("n_lines"), one),
        Rule("repeats", c("n_repeat_words") * 100 > 50 * c("n_words"), one),
        Rule("ellipsis_lines", ends * 100 > 30 * c("n_lines"), whole + c("n_lines")),
        Rule("bullet_lines", starts * 100 > 90 * c("n_lines"), whole + c("n_lines")),
        Rule("few_letters", letters * 100 < 50 * c("n_words"), c("word_chars") + c("n_words")),
        Rule("few_distinct_words", F.size(F.array_distinct(found)) * 100 < 10 * c("n_words"), c("word_chars") + 2 * c("n_words")),
    ]


def measures(docs: DataFrame) -> DataFrame:
    """Whole-text measures of every document, with text and words kept for the rules that need them."""
    text = F.coalesce(F.col("text"), F.lit(""))
    df = docs.select("doc_id", text.alias("__rc_text"))
    df = df.withColumn("__rc_words", words(F.col("__rc_text")))
    t = F.col("__rc_text")
    df = df.select(
        "doc_id", "__rc_text", "__rc_words", F.size("__rc_words").cast("long").alias("n_words"), word_chars(t).cast("long").alias("word_chars"),
        n_symbols(t).cast("long").alias("n_symbols"), n_dup_lines(t).cast("long").alias("n_dup_lines"),
        F.size(full_lines(t)).cast("long").alias("n_lines"),
    )
    df = with_repeats(df, "__rc_words", "n_repeat_words")
    return df.withColumn("n_repeat_words", F.col("n_repeat_words").cast("long"))


def sample_of(docs: DataFrame, sample_rows: int) -> DataFrame:
    """About `sample_rows` documents, chosen by a hash of id and text, the same in every run."""
    share = min(1.0, sample_rows / max(1, docs.count()))
    # a hash is below this bound for that share of all documents
    return docs.filter(F.xxhash64(F.col("doc_id"), F.col("text")) <= F.lit(int(-(2**63) + share * (2**64 - 1)))) if share < 1 else docs


def estimate(docs: DataFrame, rules_: list[Rule], sample_rows: int = 400) -> list[tuple[Rule, float, float]]:
    """(rule, work, share rejected) as means over about `sample_rows` documents, a documented bound of the estimate."""
    m = measures(sample_of(docs.select("doc_id", "text"), sample_rows))
    columns = [x for k, r in enumerate(rules_) for x in (F.avg(r.work).alias(f"w{k}"), F.avg(r.reject.cast("int")).alias(f"s{k}"))]
    row = m.agg(*columns).first()
    return [(r, row[f"w{k}"] or 0.0, row[f"s{k}"] or 0.0) for k, r in enumerate(rules_)]


def ordered(estimates: list[tuple[Rule, float, float]]) -> list[Rule]:
    """Most rejections per work first; of equal ones, the cheaper first."""
    return [r for r, work, share in sorted(estimates, key=lambda x: (-x[2] / max(x[1], 1e-6), x[1]))]


def cascade(rules_: list[Rule]) -> Column:
    """Name of the first rule that rejects, in order; null if all let it through. Later rules are not evaluated."""
    out = None
    for r in rules_:
        out = F.when(r.reject, F.lit(r.name)) if out is None else out.when(r.reject, F.lit(r.name))
    return out


def judge(docs: DataFrame, rules_: list[Rule] | None = None, sample_rows: int = 400) -> DataFrame:
    """Measures, `base_failed`, `kept` and `rejected_by` (the first rule of the cascade that rejects) of every document."""
    order = ordered(estimate(docs, rules_ or rules(), sample_rows))
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    df = measures(docs).withColumn("base_failed", failed)
    df = df.withColumn("rejected_by", F.when(F.col("base_failed"), F.lit("base")).otherwise(cascade(order)))
    return df.withColumn("kept", F.col("rejected_by").isNull()).drop("__rc_text", "__rc_words")


def quality(docs: DataFrame) -> DataFrame:
    return judge(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")
