"""Sharding by a hierarchical weighted hash tree: region, rack, shard.

A tree has a fixed shape of places, each with a capacity; a shard fills a place with a weight up to that capacity. A
key descends from the root: at each level it draws a child with odds in proportion to the capacity of the child's
subtree, by bits of one md5 of the key and the number of the attempt, so only the path taken is hashed. At the place
that it reaches, a last draw accepts it with odds weight / capacity (an empty place never does); else the key starts
again from the root with the next attempt. So it ends in a subtree with odds in proportion to the subtree's weight.
Level draws depend on capacities alone, so a changed weight changes acceptance at one place only: keys move only into
or out of the changed shard, and no draw outside its path is looked at. After ATTEMPTS refusals (2 of a million keys
with 24 of 36 places filled) the least exponential draw among all shards decides, which has the same property.

Law of the query: `key`. doc_id and the shard count decide; one more shard takes rows only into itself.

Defined cases: null doc_id is the key ''; null text has size 8 and crc 0; rows with equal doc_id share a shard;
repeated rows each get a slot of their own; an empty table gives an empty result. Extra columns are ignored. A tree
without weight, a weight above its place's capacity and more shards than places are refused. Among many buckets,
slots follow the buckets (see `number_slots`), so their order differs from that of a small table.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import accumulate

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Descents before the flat choice, and the range of a draw (eight hexadecimal digits).
ATTEMPTS, RANGE = 12, 2**32


@dataclass(frozen=True)
class Tree:
    """Places by number: `shards` in a rack, `racks` in a region. Weight 0: the place is empty."""

    regions: int
    racks: int
    shards: int
    weights: tuple[float, ...]
    capacities: tuple[float, ...]

    def __post_init__(self):
        if not len(self.weights) == len(self.capacities) == self.regions * self.racks * self.shards:
            raise ValueError("one weight and one capacity a place")
        if not any(self.weights) or any(not 0 <= w <= c for w, c in zip(self.weights, self.capacities, strict=True)):
            raise ValueError("weights lie between 0 and the capacity, and not all are 0")


def tree(n_shards: int, shape: tuple[int, int, int] = (3, 3, 4), weights: dict[int, float] | None = None, capacity: float = 1.0) -> Tree:
    """Shards 0..n-1 in the first places, with weight 1 unless given. Trees of one shape and capacity are comparable."""
    places = shape[0] * shape[1] * shape[2]
    if n_shards > places:
        raise ValueError(f"{n_shards} shards do not fit into {places} places; use a larger shape")
    filled = [(weights or {}).get(k, 1.0) if k < n_shards else 0.0 for k in range(places)]
    return Tree(*shape, tuple(filled), (capacity,) * places)


def _let(value: Column, body) -> Column:
    """body(value) with the value computed once."""
    return F.transform(F.array(value), body)[0]


def _bits(digest: Column, part: int) -> Column:
    return F.conv(F.substring(digest, 8 * part + 1, 8), 16, 10).cast("long")


def _draw_child(bits: Column, capacities: list[float]) -> Column:
    """Number of the child that the bits fall on, with odds in proportion to the capacities."""
    total = sum(capacities)
    bounds = [-int(-upto * RANGE // total) for upto in accumulate(capacities)][:-1]
    return _let(bits, lambda x: sum(((x >= F.lit(n)).cast("int") for n in bounds), F.lit(0)))


def _below(node: Column, bits: Column, sizes: list[tuple[float, ...]]) -> Column:
    """Child drawn below the node that was reached; the draws of the other nodes are not computed."""
    out = None
    for size in set(sizes):
        where = F.array(*[F.lit(s == size) for s in sizes])[node]
        out = F.when(where, _draw_child(bits, size)) if out is None else out.when(where, _draw_child(bits, size))
    return out if len(set(sizes)) > 1 else _draw_child(bits, sizes[0])


def _place(digest: Column, t: Tree) -> Column:
    """Number of the place that a digest leads to, level by level."""
    groups = [t.capacities[k : k + t.shards] for k in range(0, len(t.capacities), t.shards)]
    racks = [tuple(sum(g) for g in groups[k : k + t.racks]) for k in range(0, len(groups), t.racks)]
    region = _draw_child(_bits(digest, 0), [sum(r) for r in racks])
    rack = _let(region, lambda r: r * t.racks + _below(r, _bits(digest, 1), racks))
    return _let(rack, lambda r: r * t.shards + _below(r, _bits(digest, 2), groups))


def _accepted(place: Column, digest: Column, t: Tree) -> Column:
    """The place where the tree takes the key there, else null."""
    if all(w in (0, c) for w, c in zip(t.weights, t.capacities, strict=True)):
        return F.when(F.array(*[F.lit(w > 0) for w in t.weights])[place], place)
    odds = F.array(*[F.lit(int(w / c * RANGE) if c else 0).cast("long") for w, c in zip(t.weights, t.capacities, strict=True)])
    return F.when(_bits(digest, 3) < odds[place], place)


def flat_choice(key: Column, t: Tree) -> Column:
    """Shard of the least exponential draw -ln(u) / weight; ties go to the lower number."""
    draws = []
    for k, w in enumerate(t.weights):
        if w:
            digits = F.conv(F.substring(F.md5(F.concat(key, F.lit(f":leaf:{k}"))), 1, 13), 16, 10).cast("double")
            draws.append(F.struct((-F.log((digits + 0.5) / F.lit(2.0**52)) / F.lit(float(w))).alias("d"), F.lit(k).alias("n")))
    return F.array_min(F.array(*draws))["n"]


def descend(df: DataFrame, key: Column, trees: dict[str, Tree], attempts: int = ATTEMPTS) -> DataFrame:
    """Add the shard of each row in each of the trees, by column name; trees of one shape and capacities share their draws.

    An attempt is hashed only for rows that some tree has not taken yet. No shuffle.
    """
    if len({(t.regions, t.racks, t.shards, t.capacities) for t in trees.values()}) > 1:
        raise ValueError("trees of one descent have one shape and the same capacities")
    first = next(iter(trees.values()))

    def attempt(reached: Column, k: Column) -> Column:
        taken = F.lit(True)
        for name in trees:
            taken = taken & reached[name].isNotNull()

        def go(digest: Column) -> Column:
            return _let(_place(digest, first), lambda p: F.struct(*[F.coalesce(reached[name], _accepted(p, digest, t)).alias(name) for name, t in trees.items()]))

        return F.when(taken, reached).otherwise(_let(F.md5(F.concat(key, F.lit(":"), k.cast("string"))), go))

    nowhere = F.struct(*[F.lit(None).cast("int").alias(name) for name in trees])
    numbers = F.array(*[F.lit(k) for k in range(attempts)]).cast("array<int>")
    df = df.withColumn("__rc_reached", F.aggregate(numbers, nowhere, attempt))
    # the last 0 is never reached; it tells the optimizer that no shard is null
    found = {name: F.coalesce(F.col("__rc_reached")[name], F.when(F.col("__rc_reached")[name].isNull(), flat_choice(key, t)), F.lit(0)) for name, t in trees.items()}
    return df.withColumns(found).drop("__rc_reached")


def _key(column: str) -> Column:
    return F.coalesce(F.col(column).cast("string"), F.lit(""))


def assign(df: DataFrame, t: Tree, key: str = "doc_id", into: str = "shard") -> DataFrame:
    """Add the shard of each row."""
    return descend(df, _key(key), {into: t})


def number_slots(df: DataFrame, rows: int, n_shards: int, order: list[str], rows_per_bucket: int = 100_000) -> DataFrame:
    """Gapless `slot` from 0 in every shard.

    A shard is numbered in hash buckets of about rows_per_bucket rows: bucket counts, a running sum of them (one row
    per bucket), and row numbers within buckets, so that no task holds a shard.
    """
    buckets = max(1, -(-rows // (rows_per_bucket * n_shards)))
    df = df.withColumn("__rc_bucket", F.pmod(F.xxhash64(*order), F.lit(buckets)).cast("int"))
    counts = df.groupBy("shard", "__rc_bucket").agg(F.count(F.lit(1)).alias("n"))
    upto = Window.partitionBy("shard").orderBy("__rc_bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select("shard", "__rc_bucket", F.coalesce(F.sum("n").over(upto), F.lit(0)).alias("__rc_start"))
    within = Window.partitionBy("shard", "__rc_bucket").orderBy(*order)
    return (
        df.withColumn("__rc_n", F.row_number().over(within) - 1)
        .join(starts, ["shard", "__rc_bucket"])
        .withColumn("slot", (F.col("__rc_start") + F.col("__rc_n")).cast("long"))
        .drop("__rc_bucket", "__rc_n", "__rc_start")
    )


def shard_documents(docs: DataFrame, n_shards: int = 24, shape: tuple[int, int, int] = (3, 3, 4)) -> DataFrame:
    """The contract's columns for all documents, with region and rack after them."""
    rows = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 8).cast("long").alias("size"),
        F.crc32(F.encode(F.coalesce("text", F.lit("")), "UTF-8")).alias("text_crc32"),
    )
    rows = descend(rows, _key("doc_id"), {"shard": tree(n_shards, shape), "grown_shard": tree(n_shards + 1, shape)})
    numbered = number_slots(rows, docs.count(), n_shards, ["doc_id", "text_crc32", "size"])
    rack = F.floor(F.col("shard") / shape[2]).cast("int")
    return numbered.select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), F.col("shard").cast("int").alias("shard"), "slot",
        F.col("grown_shard").cast("int").alias("grown_shard"), F.floor(rack / shape[1]).cast("int").alias("region"), rack.alias("rack"),
    )
