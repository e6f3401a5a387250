"""Benchmark decontamination: size-partitioned MinHash containment search, in DataFrame functions only.

A document contains a test item if at least `threshold` of the item's distinct word shingles occur in it. Test items
are short and documents long, so Jaccard-based sketches of whole documents miss them; instead items are sketched and
documents are searched:

1. Items fall into partitions by their number of shingles (powers of two). Every item keeps as its sketch its least
   K min-hash values, K = 2 m + 1 with m the most shingles that an item of its partition may miss. An item of n
   shingles with the required containment misses at most n - ceil(threshold * n) of them, so all but that many of its
   sketch values are in the document: `hits` of them at least, and no miss.
2. Distinct shingle hashes of the documents meet the sketches only, never the items' other shingles. A text and an
   item with `hits` common sketch values are a candidate.
3. Candidates alone are verified: the document's whole shingle set is intersected with the item's.

Shingles are five lower-cased words; an item with fewer words is one shingle of its own length, and is looked for at
that length. Candidates name a text by a 64-bit hash; two texts with one hash would both be verified. Defined cases:
null or empty texts have no shingles and neither match nor are matched; repeated items each match under their item_id;
repeated documents each match; extra columns are ignored; empty tables give an empty result. Sketches are broadcast up
to `broadcast_rows` values, and candidates up to as many rows (both counted first); beyond that the join shuffles.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from regioncount.llm.common import Scratch
from regioncount.llm.op7_quality import words


def lowered(text: Column) -> Column:
    """A-Z to a-z, other characters as they are."""
    return F.translate(F.coalesce(text, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def shingles(w: Column, size: int) -> Column:
    """Distinct 64-bit hashes of the runs of `size` words; none if there are fewer words."""
    runs = F.transform(F.sequence(F.lit(0), F.size(w) - size), lambda i: F.xxhash64(F.lit(size), *[F.get(w, i + k) for k in range(size)]))
    return F.array_distinct(F.when(F.size(w) >= size, runs).otherwise(F.array().cast("array<bigint>")))


def item_sets(items: DataFrame, size: int = 5, threshold: float = 0.8) -> DataFrame:
    """(item_id, uid, part, n, need, hs): the sorted distinct shingles of each item."""
    df = items.select("item_id", words(lowered(F.col("text"))).alias("w"), F.monotonically_increasing_id().alias("uid"))
    hashes = F.when(F.size("w") >= size, shingles(F.col("w"), size))
    for k in range(1, size):
        hashes = hashes.when(F.size("w") == k, shingles(F.col("w"), k))
    df = df.withColumn("hs", F.sort_array(hashes)).filter(F.size("hs") > 0).drop("w")
    df = df.withColumn("n", F.size("hs")).withColumn("need", F.ceil(F.col("n") * F.lit(threshold) - F.lit(1e-9)).cast("int"))
    return df.withColumn("part", F.floor(F.log2(F.col("n"))).cast("int"))


def item_sketches(sets: DataFrame) -> DataFrame:
    """(uid, part, hits, h): a row for each sketch value of each item; `hits` of an item's are in what contains it."""
    worst = sets.groupBy("part").agg((2 * F.max(F.col("n") - F.col("need")) + 1).alias("k"))
    df = sets.join(F.broadcast(worst), "part").withColumn("k", F.least("k", "n"))
    return df.select("uid", "part", (F.col("k") - (F.col("n") - F.col("need"))).alias("hits"), F.explode(F.slice("hs", F.lit(1), F.col("k"))).alias("h"))


def all_shingles(w: Column, lengths: list[int]) -> Column:
    """Distinct shingles of these lengths. `w` must be a column that an earlier select made, so that it is split once."""
    return F.concat(*[shingles(w, k) for k in lengths]) if len(lengths) > 1 else shingles(w, lengths[0])


def candidates(docs: DataFrame, sketches: DataFrame, lengths: list[int], broadcast: bool) -> DataFrame:
    """(key, uid): hashes of texts that hold enough sketch values of an item, and the item."""
    seen = docs.select(F.xxhash64("text").alias("key"), F.monotonically_increasing_id().alias("row"), words(lowered(F.col("text"))).alias("w"))
    seen = seen.select("key", "row", F.explode(all_shingles(F.col("w"), lengths)).alias("h"))
    found = seen.join(F.broadcast(sketches) if broadcast else sketches, "h")
    found = found.groupBy("row", "key", "uid").agg(F.count(F.lit(1)).alias("c"), F.first("hits").alias("hits"))
    return found.filter("c >= hits").select("key", "uid").distinct()


def contained(docs: DataFrame, items: DataFrame, size: int = 5, threshold: float = 0.8, broadcast_rows: int = 500_000, keep: tuple[str, ...] = ()) -> DataFrame:
    """(doc_id, item_id, n_shingles, n_shared): all pairs with at least the required containment; and the columns of
    docs named in `keep`."""
    scratch = Scratch(docs.sparkSession)
    sets = scratch.save(item_sets(items, size, threshold), "items")
    sketches = scratch.save(item_sketches(sets), "sketches")
    n_values = sketches.count()
    lengths = [size]
    if sets.filter("n = 1").limit(1).count():  # some items may have fewer words than a shingle
        lengths = sorted({r[0] for r in items.select(F.least(F.size(words(lowered(F.col("text")))), F.lit(size)).alias("k")).distinct().collect()} - {0} | {size})
    pairs = scratch.save(candidates(docs, sketches, lengths, n_values <= broadcast_rows), "candidates")
    scratch.drop(sketches)
    few = (lambda df: F.broadcast(df)) if pairs.count() <= broadcast_rows else (lambda df: df)
    texts = docs.select("doc_id", *keep, "text", F.xxhash64("text").alias("key")).join(few(pairs.select("key").distinct()), "key", "left_semi")
    texts = texts.select("doc_id", *keep, "key", words(lowered(F.col("text"))).alias("__rc_w"))
    texts = texts.select("doc_id", *keep, "key", all_shingles(F.col("__rc_w"), lengths).alias("seen"))
    whole = sets.select("uid", "item_id", "n", "need", "hs")
    found = texts.join(few(pairs), "key").join(F.broadcast(whole) if n_values <= broadcast_rows else whole, "uid")
    found = found.withColumn("shared", F.size(F.array_intersect("hs", "seen"))).filter("shared >= need")
    return found.select("doc_id", "item_id", F.col("n").cast("long").alias("n_shingles"), F.col("shared").cast("long").alias("n_shared"), *keep)


def decontaminate(docs: DataFrame, items: DataFrame, broadcast_rows: int = 500_000) -> DataFrame:
    """Rows that contain no test item, with all their columns. Each row goes or stays by its own text, whatever other
    rows share its doc_id or have none; null and empty texts stay, and so do all rows where there are no items."""
    digest = F.unhex(F.md5(F.col("text").cast("binary")))
    found = contained(docs.select("doc_id", "text", digest.alias("__rc_digest")), items, keep=("__rc_digest",))
    scratch = Scratch(docs.sparkSession)
    bad = scratch.save(found.select(F.col("doc_id").alias("__rc_bad"), "__rc_digest").distinct(), "bad")
    bad = F.broadcast(bad) if bad.count() <= broadcast_rows else bad
    return docs.join(bad, F.col("doc_id").eqNullSafe(F.col("__rc_bad")) & (digest == F.col("__rc_digest")), "left_anti")
