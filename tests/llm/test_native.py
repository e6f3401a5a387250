"""Sharding, quality rules and decontamination."""

import hashlib
import math
import random
import zlib

import pytest
from pyspark.sql import functions as F

from regioncount.llm import op1_sharding as s
from regioncount.llm import op7_quality as q
from regioncount.llm import op9_decontamination as dc


def python_free(df):
    plan = df._jdf.queryExecution().toString()
    return not any(x in plan for x in ("Python", "Pandas", "Arrow", "CartesianProduct"))


def test_shards(spark, messy, no_documents):
    df = s.shard_documents(messy, 24)
    assert python_free(df)
    rows = df.collect()
    assert len(rows) == messy.count() and s.shard_documents(no_documents, 24).count() == 0
    for shard in {r.shard for r in rows}:
        assert sorted(r.slot for r in rows if r.shard == shard) == list(range(sum(r.shard == shard for r in rows)))
    by_id = {}
    for r in rows:
        assert by_id.setdefault(r.doc_id, r.shard) == r.shard and r.grown_shard in (r.shard, 24)
        assert r.region == r.shard // 12 and r.rack == r.shard // 4
    texts = {(r.doc_id, r.text or "") for r in messy.collect()}
    assert {(r.doc_id, r.text_crc32, r.size) for r in rows} == {(i, zlib.crc32(t.encode()), len(t.encode()) + 8) for i, t in texts}


def test_shards_grow_evenly_and_only_into_the_new_one(spark):
    ids = spark.range(6000).withColumnRenamed("id", "doc_id")
    a = s.assign(s.assign(ids, s.tree(24), into="a"), s.tree(25), into="b")
    moved = a.filter("a <> b")
    assert moved.filter("b <> 24").count() == 0 and 120 < moved.count() < 380
    sizes = [r["count"] for r in a.groupBy("a").count().collect()]
    assert len(sizes) == 24 and min(sizes) > 170 and max(sizes) < 340


def test_weights_move_rows_only_at_the_changed_leaf(spark):
    ids = spark.range(4000).withColumnRenamed("id", "doc_id")
    for attempts in (0, 1, 12):  # the flat choice alone, mostly, and hardly ever
        a = s.descend(ids, s._key("doc_id"), {"a": s.tree(12, (1, 3, 4), None, 4.0), "b": s.tree(12, (1, 3, 4), {5: 3.0}, 4.0)}, attempts)
        assert python_free(a) and a.filter("a <> b and b <> 5").count() == 0
        assert abs(a.filter("b = 5").count() - 4000 * 3 / 14) < 160


def descend_plainly(key, t):
    """(place, digests made) of a key by loops over levels."""
    for k in range(s.ATTEMPTS):
        digest = hashlib.md5(f"{key}:{k}".encode()).hexdigest()
        bits = [int(digest[8 * i : 8 * i + 8], 16) for i in range(4)]
        low, high = 0, len(t.weights)
        for level, width in enumerate((t.racks * t.shards, t.shards, 1)):
            sizes = [sum(t.capacities[x : x + width]) for x in range(low, high, width)]
            at = 0
            while bits[level] * sum(sizes) >= sum(sizes[: at + 1]) * 2**32:
                at += 1
            low, high = low + at * width, low + (at + 1) * width
        if bits[3] < t.weights[low] / t.capacities[low] * 2**32:
            return low, k + 1
    return min(((-math.log((int(hashlib.md5(f"{key}:leaf:{x}".encode()).hexdigest()[:13], 16) + 0.5) / 2**52) / w, x) for x, w in enumerate(t.weights) if w))[1], s.ATTEMPTS


def test_descent_against_plain_loops(spark):
    """Uneven capacities and weights at all levels; subtrees get their weight's share, and few digests are made."""
    rng = random.Random(3)
    capacities = tuple(float(rng.choice([1, 2, 4, 8])) for _ in range(24))
    t = s.Tree(2, 3, 4, tuple(0.0 if k % 7 == 3 else c * rng.choice([0.5, 1.0, 0.75]) for k, c in enumerate(capacities)), capacities)
    ids = spark.range(3000).withColumnRenamed("id", "doc_id")
    got = {r.doc_id: r.shard for r in s.assign(ids, t).collect()}
    want = {k: descend_plainly(k, t) for k in got}
    assert got == {k: v[0] for k, v in want.items()}
    assert sum(v[1] for v in want.values()) < 2.2 * len(want)
    for at in range(0, 24, 4):
        share = sum(t.weights[at : at + 4]) / sum(t.weights)
        assert abs(sum(at <= v < at + 4 for v in got.values()) / 3000 - share) < 0.04
    for bad in (lambda: s.tree(40), lambda: s.tree(2, weights={0: 2.0}), lambda: s.tree(0), lambda: s.descend(ids, s._key("doc_id"), {"a": s.tree(3), "b": s.tree(3, (1, 1, 4))})):
        with pytest.raises(ValueError):
            bad()


def test_slots_over_many_buckets(spark):
    df = spark.range(500).select((F.col("id") % 3).cast("int").alias("shard"), F.col("id").alias("doc_id"))
    rows = s.number_slots(df, 500, 3, ["doc_id"], rows_per_bucket=20).collect()
    for k in range(3):
        assert sorted(r.slot for r in rows if r.shard == k) == list(range(sum(r.shard == k for r in rows)))


def brute_quality(text):
    words = [w for w in text.encode().split()]
    lines = [x for x in text.split("\n") if x.encode().strip(b" \t\n\x0b\x0c\r")]
    grams = {}
    for i in range(len(words) - 2):
        grams.setdefault(tuple(words[i : i + 3]), []).append(i)
    inside = {i + k for at in grams.values() if len(at) > 1 for i in at for k in range(3)}
    return len(words), sum(len(w.decode()) for w in words), sum(c in "#*$%&|<>" for c in text), len(lines) - len(set(lines)), len(inside)


def test_quality(spark, messy, no_documents):
    df = q.quality(messy)
    assert python_free(df) and q.quality(no_documents).count() == 0
    want = sorted((str(r.doc_id), *brute_quality(r.text or "")) for r in messy.collect())
    assert sorted((str(r.doc_id), r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in df.collect()) == want
    for r in df.collect():
        assert r.base_failed == (r.n_words < 50 or 100 * r.n_repeat_words > 50 * r.n_words) and not (r.kept and r.base_failed)


def test_cascade_order_does_not_change_the_verdict(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    m, rules = q.measures(docs), q.rules()
    a = m.select("doc_id", q.cascade(rules).isNull().alias("k"))
    b = m.select("doc_id", q.cascade(rules[::-1]).isNull().alias("k"))
    assert a.exceptAll(b).count() == 0
    est = q.estimate(docs, rules, 50)
    assert [x[1:] for x in est] == [x[1:] for x in q.estimate(docs, rules, 50)]
    order = q.ordered(est)
    share = {r.name: x / max(c, 1e-6) for r, c, x in est}
    assert [share[r.name] for r in order] == sorted(share.values(), reverse=True)
    assert 20 < q.sample_of(docs, 50).count() < 90 and q.sample_of(docs, 10**6).count() == docs.count()


def test_rejected_documents_reach_no_later_rule(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    boom = q.Rule("boom", F.raise_error(F.lit("evaluated")).cast("boolean"), F.lit(10**6))
    first = q.Rule("all", F.col("n_words") >= 0, F.lit(1))
    m = q.measures(docs)
    assert m.filter(q.cascade([first, boom]) == "all").count() == docs.count()
    # only texts of the few that pass reach the costly rule
    only = q.Rule("some", F.col("n_words") != F.lit(m.agg(F.max("n_words")).first()[0]), F.lit(1))
    guarded = q.Rule("guarded", F.when(F.col("n_words") < 60, boom.reject).otherwise(F.lit(True)), F.lit(5))
    assert {r[0] for r in m.select(q.cascade([only, guarded])).distinct().collect()} == {"some", "guarded"}


def test_rules_inside_the_cascade(spark):
    w = [f"word{k}" for k in range(60)]
    texts = {
        "ellipsis_lines": "\n".join(" ".join(w[k : k + 10]) + end for k, end in zip(range(0, 60, 10), ("...", "\u2026 ", "", "", "..", ""), strict=True)),
        "bullet_lines": "\n".join(f" {mark} " + " ".join(w[k : k + 10]) for k, mark in zip(range(0, 60, 10), "-*\u2022-*-", strict=True)),
        "few_letters": " ".join([*w[:25], *(str(1000 + k) for k in range(30))]),
        None: " ".join(w),
        "few_distinct_words": " ".join(random.Random(2).choice(["aa", "bb", "cc", "dd", "ee", "ff", "gg"]) for _ in range(75)),
    }
    docs = spark.createDataFrame([(k, x) for k, x in enumerate(texts.values())], "doc_id long, text string")
    m = q.measures(docs).filter("doc_id < 5")
    last = q.rules()[6:]
    assert [r.c for r in m.select("doc_id", q.cascade(last).alias("c")).orderBy("doc_id").collect()] == list(texts)
    got = {r.doc_id: r.kept for r in q.judge(docs).collect()}
    assert got == {0: False, 1: False, 2: False, 3: True, 4: False}


def test_decontamination(spark, messy, no_documents):
    rng_words = [f"w{k}" for k in range(40)]
    passage = " ".join(rng_words)
    near = " ".join(rng_words[:36] + ["other"] + rng_words[37:])
    far = " ".join(rng_words[:25])
    docs = messy.select("doc_id", "text", "score").union(spark.createDataFrame([(100, "intro " + passage.upper() + " end", "x"), (101, "a b c " * 500 + near, "x"), (102, far, "x"), (103, "only tiny here", "x"), (104, "tiny", "x")], "doc_id long, text string, score string"))
    items = spark.createDataFrame([(1, passage), (2, passage), (3, None), (4, ""), (5, "tiny")], "item_id long, text string")
    found = dc.contained(docs, items)
    assert python_free(found)
    assert {(r.doc_id, r.item_id) for r in found.collect()} == {(100, 1), (100, 2), (101, 1), (101, 2), (103, 5), (104, 5)}
    assert {(r.doc_id, r.item_id) for r in dc.contained(docs, items, broadcast_rows=0).collect()} == {(r.doc_id, r.item_id) for r in found.collect()}
    kept = dc.decontaminate(docs, items)
    assert kept.columns == docs.columns and kept.count() == docs.count() - 4
    assert dc.contained(docs, items.limit(0)).count() == 0 and dc.contained(no_documents, items).count() == 0
    assert dc.decontaminate(docs, items.limit(0)).count() == docs.count()


def test_sketches_prune_before_verification(spark):
    """Only texts with enough sketch values are candidates; the sketch alone does not decide; nothing is missed."""
    w = [f"w{k}" for k in range(104)]  # 100 shingles: 20 may be missing, 41 sketch values, 21 hits
    rng = random.Random(5)
    texts = {0: " ".join(w), 1: " ".join(w[:30]), 2: "no word of it", 3: " ".join(w[:24])}
    for k in range(4, 60):
        cut = rng.randint(60, 104)
        at = rng.randint(0, 104 - cut)
        texts[k] = " ".join(["x", *w[at : at + cut], "y"])
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    items = spark.createDataFrame([(1, texts[0]), (2, "other words that nobody uses at all here")], "item_id long, text string")
    sets = dc.item_sets(items)
    sketches = dc.item_sketches(sets)
    assert sets.count() == 2 and {(r.n, r.c, r.hits) for r in sketches.groupBy("uid", "hits").agg(F.count("*").alias("c")).join(sets, "uid").collect()} == {(100, 41, 21), (4, 1, 1)}
    named = docs.select("doc_id", F.xxhash64("text").alias("key"))
    cand = {r.doc_id for r in dc.candidates(docs, sketches, [5], True).join(named, "key").collect()}
    found = {r.doc_id: r.n_shared for r in dc.contained(docs, items).collect()}
    sure = {k: max(0, sum(f" {' '.join(w[i : i + 5])} " in f" {t} " for i in range(100))) for k, t in texts.items()}
    assert found == {k: c for k, c in sure.items() if c >= 80}
    touching = {k for k, c in sure.items() if c}
    assert set(found) < cand < touching and not cand & {2, 3}


def test_decontamination_decides_by_row(spark):
    passage = " ".join(f"w{k}" for k in range(40))
    rows = [(None, "clean without a number", 1), (None, f"intro {passage}", 2), (None, None, 3), (7, f"{passage} end", 4), (7, "clean under the same number", 5), (8, "clean", 6), (9, f"{passage} end", 7), (9, f"{passage} end", 8), (8, "clean", 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_chars long")
    kept = dc.decontaminate(docs, spark.createDataFrame([(1, passage)], "item_id long, text string"))
    assert python_free(kept) and kept.columns == docs.columns
    assert sorted(r.n_chars for r in kept.collect()) == [1, 3, 5, 6, 9]
