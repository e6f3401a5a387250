"""URL filter: rules first, then gradient-boosted trees on lexical features.

Rules block or allow a host with its subdomains below a path; the longest that fits decides. For other URLs the
trees decide by length, depth, digit share, entropy, counts of parameters and marks, and suffix statistics (the
smoothed share of bad URLs among all labelled URLs below the same last one and three host labels; for a training URL
its own label is left out).

The trees are trained here from labelled URLs, at most `rows` (a documented bound); the suffix statistics are counted
over every labelled URL and joined, by broadcast up to `broadcast_rows` suffixes. The query labels URLs of the
corpus itself by the words of their hosts' labels: bad if one is in BAD_WORDS. That is the weak supervision of
published URL filters; a table of labelled URLs takes its place where there is one.

Defined cases: a null URL or one without :// has empty host and path, fits no rule, and is judged by its (empty)
features; A-Z of hosts is lower-cased, paths are kept; very long URLs are read whole; repeated rows are judged one by
one; extra columns are ignored; with an empty table, or labels of one class only, trees allow all.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from regioncount.llm import gbt

#: Fixed values of the contract: (host, path, verdict).
RULES = (("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block"))
#: Words of host labels that make a training URL a bad one.
BAD_WORDS = ("adult", "ads", "bet", "bets", "casino", "cheap", "farm", "free", "pills", "poker", "porn", "promo", "sex", "spam", "track", "viagra", "win", "xxx")
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
FEATURES = ("length", "host_length", "host_labels", "longest_label", "path_length", "depth", "digits", "digit_share", "host_digits", "hyphens", "host_hyphens", "entropy", "host_entropy", "parameters", "query_length", "marks", "vowel_share", "fragment", "https", "suffix1", "suffix2")


def host(url: Column) -> Column:
    return F.translate(F.coalesce(F.regexp_extract(url, r"(?s)^.*?://([^/?#]*)", 1), F.lit("")), UPPER, LOWER)


def path(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(url, r"(?s)^.*?://[^/?#]*([^?#]*)", 1), F.lit(""))


def fits(host_column: Column, path_column: Column, rule: tuple[str, str, str]) -> Column:
    name, start, _ = rule
    return ((host_column == name) | host_column.endswith(f".{name}")) & path_column.startswith(start)


def judge_by_rules(df: DataFrame, rules=RULES) -> DataFrame:
    """Add `rule` and `rule_verdict`: of the longest rule that fits `host` and `path`, else null."""
    rule = verdict = None
    for r in sorted(rules, key=lambda r: -len(r[0] + r[1])):
        hit, name = fits(F.col("host"), F.col("path"), r), F.lit(r[0] + r[1])
        rule = F.when(hit, name) if rule is None else rule.when(hit, name)
        verdict = F.when(hit, F.lit(r[2])) if verdict is None else verdict.when(hit, F.lit(r[2]))
    nothing = F.lit(None).cast("string")
    return df.withColumn("rule", rule if rule is not None else nothing).withColumn("rule_verdict", verdict if verdict is not None else nothing)


def entropy(text: str) -> float:
    n = len(text)
    return -sum(c / n * math.log2(c / n) for c in Counter(text).values()) if n else 0.0


def parts(url: str) -> tuple[str, str, str, str]:
    """(host, path, query, fragment)"""
    if "://" not in url:
        return "", "", "", ""
    m = re.match(r"([^/?#]*)([^?#]*)(?:\?([^#]*))?(?:#(.*))?", url.split("://", 1)[1], re.S)
    return m[1].translate(str.maketrans(UPPER, LOWER)), m[2], m[3] or "", m[4] or ""


def suffix_columns(name: Column) -> list[Column]:
    """`suffixes` of a column of hosts."""
    return [F.substring_index(name, ".", -1), F.substring_index(name, ".", -3)]


def suffixes(name: str) -> tuple[str, str]:
    labels = name.split(".")
    return labels[-1], ".".join(labels[-3:])


def lexical(url: str) -> list[float]:
    h, p, q, frag = parts(url)
    n_digits = sum(c.isdigit() for c in url)
    letters = [c for c in h if c.isalpha()]
    return [
        len(url), len(h), h.count(".") + 1, max(map(len, h.split("."))), len(p), p.count("/"), n_digits, n_digits / max(1, len(url)), sum(c.isdigit() for c in h), url.count("-"), h.count("-"),
        entropy(url), entropy(h), len(re.findall(r"[^&=]+=", q)), len(q), sum(c in "_~%@;,!$" for c in url), sum(c in "aeiou" for c in letters) / max(1, len(letters)), len(frag), float(url.startswith("https")),
    ]


@dataclass
class Filter:
    trees: gbt.Trees | None
    #: Suffix to (bad, all) among the training URLs.
    counts: dict[str, tuple[int, int]] = field(default_factory=dict)
    share: float = 0.0

    def statistics(self, url: str, label: int | None = None) -> list[float]:
        """Smoothed shares of bad URLs; `label` is taken out again if this URL is a training one."""
        out = []
        for s in suffixes(parts(url)[0]):
            bad, n = self.counts.get(s, (0, 0))
            if label is not None:
                bad, n = bad - label, n - 1
            out.append((bad + 5 * self.share) / (n + 5))
        return out

    def scores(self, urls: list[str], statistics: list[list[float]] | None = None) -> np.ndarray:
        if self.trees is None or not urls:
            return np.zeros(len(urls))
        statistics = [self.statistics(u) for u in urls] if statistics is None else statistics
        return self.trees.probabilities(np.array([lexical(u) + s for u, s in zip(urls, statistics, strict=True)]))


def train(urls: list[str], labels: list[int], counts: dict[str, tuple[int, int]] | None = None, share: float | None = None) -> Filter:
    """`counts` and `share` are those of a larger set of labelled URLs; without them they are taken from these."""
    if len(set(labels)) < 2:
        return Filter(None)
    found = Filter(None, share=sum(labels) / len(labels) if share is None else share)
    bad, n = Counter(), Counter()
    for u, y in zip(urls, labels, strict=True):
        for s in suffixes(parts(u)[0]):
            n[s] += 1
            bad[s] += y
    found.counts = {s: (bad[s], n[s]) for s in n} if counts is None else counts
    x = np.array([lexical(u) + found.statistics(u, y) for u, y in zip(urls, labels, strict=True)])
    found.trees = gbt.fit(x, np.array(labels, float), trees=40, depth=4)
    return found


def weak_labels(pages: DataFrame) -> DataFrame:
    """(url, label): 1 if a word of the host is in BAD_WORDS."""
    names = F.split(host(F.col("url")), "[^a-z]+")
    return pages.select("url", F.arrays_overlap(names, F.array(*[F.lit(w) for w in BAD_WORDS])).cast("int").alias("label")).filter(F.col("url").isNotNull())


def suffix_counts(labelled: DataFrame) -> DataFrame:
    """(suffix, bad, n) over all labelled URLs."""
    rows = labelled.select("label", F.explode(F.array(*suffix_columns(host(F.col("url"))))).alias("suffix"))
    return rows.groupBy("suffix").agg(F.sum("label").alias("bad"), F.count(F.lit(1)).alias("n"))


def fit(labelled: DataFrame, rows: int = 12_000) -> Filter:
    """Trees of at most `rows` labelled URLs, which a hash of the URL picks; suffix statistics of all labelled URLs,
    kept for the suffixes of the picked ones."""
    picked = labelled.select("url", "label").orderBy(F.xxhash64("url"), "url", "label").limit(rows).collect()
    names = sorted({(s,) for r in picked for s in suffixes(parts(r["url"])[0])})
    few = F.broadcast(labelled.sparkSession.createDataFrame(names, "suffix string"))
    counts = {r["suffix"]: (r["bad"], r["n"]) for r in suffix_counts(labelled).join(few, "suffix", "left_semi").collect()}
    return train([r["url"] for r in picked], [r["label"] for r in picked], counts, labelled.agg(F.avg("label")).first()[0])


def with_scores(df: DataFrame, model: Filter, id_column: str = "page_id", counts: DataFrame | None = None, broadcast_rows: int = 500_000) -> DataFrame:
    """Add `score`; suffix statistics come from `counts` (suffix, bad, n), or else from the model."""
    shared = df.sparkSession.sparkContext.broadcast(model)
    kind = df.schema[id_column].dataType.simpleString()
    df = df.select(id_column, "url")
    if counts is not None:
        small = counts.limit(broadcast_rows + 1).count() <= broadcast_rows
        for k, suffix in enumerate(suffix_columns(host(F.col("url")))):
            side = counts.select(F.col("suffix").alias(f"__rc_s{k}"), ((F.col("bad") + F.lit(5 * model.share)) / (F.col("n") + 5)).alias(f"__rc_p{k}"))
            df = df.withColumn("__rc_s", suffix).join(F.broadcast(side) if small else side, F.col("__rc_s") == F.col(f"__rc_s{k}"), "left").drop("__rc_s", f"__rc_s{k}")
        df = df.select(id_column, "url", *[F.coalesce(f"__rc_p{k}", F.lit(float(model.share))).alias(f"p{k}") for k in range(2)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = None if batch.num_columns < 4 else [list(p) for p in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
            scores = shared.value.scores([x or "" for x in batch.column(1).to_pylist()], found)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(scores, pa.float64())], names=[id_column, "url", "score"])

    return df.mapInArrow(run, f"{id_column} {kind}, url string, score double")


def judge(pages: DataFrame, model: Filter | None = None, rules=RULES) -> DataFrame:
    """(page_id, host, path, rule, verdict, score) of every URL."""
    counts = None
    if model is None:
        labelled = weak_labels(pages)
        model, counts = fit(labelled), suffix_counts(labelled)
    df = with_scores(pages, model, counts=counts)
    df = judge_by_rules(df.withColumn("host", host(F.col("url"))).withColumn("path", path(F.col("url"))), rules)
    verdict = F.coalesce("rule_verdict", F.when(F.col("score") >= 0.5, F.lit("block")).otherwise(F.lit("allow")))
    return df.select("page_id", "host", "path", "rule", verdict.alias("verdict"), F.round("score", 6).alias("score"))
