"""N-gram Jaccard join by T-occurrence search over inverted lists, with DivideSkip.

Two documents link when the Jaccard similarity of their sets of word shingles is at least pct/100; then the shingles
of one occur at least T times in total among the inverted lists that the other's shingles name. DivideSkip finds the
documents that occur T times without reading all lists: the L longest lists are set aside, the short ones are merged
by a heap that skips documents which cannot reach T - L, and whoever occurs T - L times there is looked up in the long
lists by binary search.

Lists of the whole corpus fit no task, so documents are first brought together:

1. Documents become sets of 64-bit shingle hashes; equal sets are one class (a 128-bit digest) with one number, and
   one row of it goes on. Copies are never paired.
2. A first T-occurrence test over all classes: each class gives its least |x| - T + k hashes; a partner must share
   k - 1 of these, so a class of whose hashes fewer than that occur elsewhere has no partner. Hashes meet in one
   shuffle. Very frequent ones, found on a sample, occur elsewhere for certain and are spread over all tasks.
3. The rest is divided by an exact partition scheme: similar sets differ in at most D hashes, so that among more than
   D parts of the hash range one part at least is equal in both. Hashes with very long lists are set aside here too.
   Classes with an equal part belong to one block. From here on classes are named by their numbers. Short texts that
   share a line chain into a block that grows with the corpus; a block over `chunk_hashes` is replaced by its groups:
   the least class that has a part, and all classes that share a part with it as the least. Two with an equal part are
   in the group of its least class.
4. DivideSkip runs in every block on whole sets, and its counts are the overlaps (of 64-bit hashes). Blocks over
   `chunk_hashes` are cut into chunks: each chunk is searched, then one member of each component found in each chunk,
   and at last those outside the block's largest component against every chunk; documents already connected are never
   compared again.
5. Blocks of one chunk give their components themselves; those of several chunks go through `components`.

Every step loses no link: 2 and 3 are pigeonhole bounds, 4 tests all pairs of a block that are not yet connected.
Intermediate tables are written to the shared folder and deleted as soon as nothing reads them. What is shuffled with
hashes is made in passes, of `pass_hashes` or an eighth of all at least, so that the files of one pass are on disk at once.

Defined cases: null, empty and white-space texts have the empty set and link with nothing; texts of fewer words than a
shingle are one shingle of all their words; repeated rows and equal texts are one class; a null doc_id takes part, and
component_id is the least doc_id that is not null; ties of size go by number; extra columns are ignored by
`components_of` and kept by `keep_one`; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import heapq
from bisect import bisect_left, bisect_right
from collections.abc import Iterator
from itertools import accumulate, pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from regioncount.llm.common import Hashes, Scratch, give_back, slices, spread_join
from regioncount.llm.components import components

_M = np.uint64(0x9E3779B97F4A7C15)
#: Words that a task remembers.
WORDS = 200_000
#: Short lists of up to this many postings in all go through the heap; where a block holds very many near copies, longer
#: ones are merged as sorted runs, which gives the same and takes less time than a heap of Python objects.
HEAP_POSTINGS = 4096
#: Hashes that a pass shuffles at least.
PASS_HASHES = 16_000_000


# ---------------------------------------------------------------- sets
def _mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads them."""
    x = (x ^ (x >> np.uint64(32))) * _M
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def word_hashes(text: bytes, seen: Hashes) -> np.ndarray:
    """Hashes of the lower-cased (A-Z) words between ASCII white space."""
    words = text.lower().split()
    return np.fromiter(map(seen.__getitem__, words), np.uint64, len(words))


def shingle_set(words: np.ndarray, k: int) -> np.ndarray:
    """Sorted distinct hashes of the runs of k words; of all words if there are fewer; empty without words."""
    if not len(words):
        return words
    size = min(k, len(words))
    acc = np.zeros(len(words) - size + 1, np.uint64)
    for i in range(size):
        acc = _mix(acc + words[i : len(words) - size + 1 + i])
    return np.unique(_mix(acc + np.uint64(size)))


def self_overlap(n: int, pct: int) -> int:
    """Least overlap of a set of n hashes with any partner."""
    return -(-pct * n // 100)


def prefix_rule(n: int, pct: int) -> tuple[int, int]:
    """(length of the prefix, k): of the least |x| - T + k hashes a partner of the same size or more shares k, and a
    smaller partner k - 1 at least (its own T and k fall with its size; rounding can cost one)."""
    t = self_overlap(n, pct)
    k = min(t, max(1, (100 - pct) * n // 200))
    return n - t + k, k


def list_column(lists: list[np.ndarray]) -> pa.ListArray:
    offsets = np.fromiter(accumulate(map(len, lists), initial=0), np.int32, len(lists) + 1)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(lists) if lists else np.zeros(0, np.int64)))


def set_rows(docs: DataFrame, k: int, pct: int, whole: bool) -> DataFrame:
    """(doc_id, cid, n, hashes): the class digest, the set size, and the prefix of the set; or, if `whole`, the set, in
    rows of which a task gives one for each (doc_id, class) among those that it remembers."""
    docs = docs.select("doc_id", docs["text"].cast("binary").alias("text"))
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen, given = Hashes(), set()
        for batch in slices(batches):
            seen.trim(WORDS)
            rows, cids, sizes, lists = [], [], [], []
            for at, x in enumerate(batch.column(1)):
                s = shingle_set(word_hashes(x.as_py() or b"", seen), k)
                cid = hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None
                if whole:
                    if cid in given:
                        continue
                    if len(given) >= WORDS:
                        given.clear()
                    given.add(cid)
                rows.append(at)
                cids.append(cid)
                sizes.append(len(s))
                lists.append((s if whole else s[: prefix_rule(len(s), pct)[0]]).view(np.int64))
            ids = batch.column(0).take(pa.array(rows, pa.int32())) if whole else batch.column(0)
            yield pa.RecordBatch.from_arrays([ids, pa.array(cids, pa.binary()), pa.array(sizes, pa.int32()), list_column(lists)], names=["doc_id", "cid", "n", "hashes"])
        give_back()

    return docs.mapInArrow(run, f"doc_id {kind}, cid binary, n int, hashes array<bigint>")


# ---------------------------------------------------------------- the exact partition scheme
def bands(pct: int, top: int) -> list[int]:
    """Least sizes of the size bands up to `top`: partners are in the same or the next band."""
    out = [1]
    while out[-1] <= top:
        out.append(100 * out[-1] // pct + 1)
    return out


def level_rule(level: int, edges: list[int], pct: int) -> tuple[int, int]:
    """(most differences D, number of parts) for pairs whose smaller set is in band `level`."""
    largest = edges[level + 1] - 1
    d = (100 - pct) * (largest + 100 * largest // pct) // (100 + pct)
    return d, d + 1 + d // 12


def signatures(s: np.ndarray, edges: list[int], pct: int, common: np.ndarray | None = None) -> np.ndarray:
    """Hashes of the parts of a set, for its own band and the one below. An empty part counts only where so many are
    empty that the equal part of a pair might be one of them.

    `common` (sorted) holds hashes that are left out of the parts: sets that differ in at most D hashes do so without
    them as well, and long lists no longer make parts equal by themselves.
    """
    h, out = s.view(np.uint64), []
    band = bisect_right(edges, len(h)) - 1
    if common is not None and len(common):
        h = h[common[np.minimum(np.searchsorted(common, h), len(common) - 1)] != h]
    spread = _mix(h)
    for level in (band, band - 1):
        if level < 0:
            continue
        d, m = level_rule(level, edges, pct)
        part = ((h >> np.uint64(32)) * np.uint64(m)) >> np.uint64(32)
        first = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1]])) if len(part) else np.zeros(0, int)
        if len(first):
            key = _mix(part[first] + np.uint64(level) * np.uint64(1 << 32))
            out.append(_mix(np.add.reduceat(spread, first) ^ key))
        if m - len(first) >= m - d:
            empty = np.setdiff1d(np.arange(m, dtype=np.uint64), part[first])
            out.append(_mix(_mix(empty + np.uint64(level) * np.uint64(1 << 32)) + np.uint64(1)))
    return np.unique(np.concatenate(out)).view(np.int64)


def common_hashes(sets: DataFrame, n_sets: int, n_hashes: int, share: float = 0.01, most: int = 500_000) -> np.ndarray:
    """Hashes in at least `share` of all sets: those with the longest lists. Any choice is safe.

    There are at most n_hashes / (share * n_sets) of them; `share` rises until that is `most`. A hash in that share of
    all sets has it in some partition, so each partition passes on only those that have it there.
    """
    share = max(share, n_hashes / n_sets / most)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, n = None, 0
        for batch in slices(batches, 2048):
            column = batch.column(0)
            off = np.asarray(column.offsets)
            n += batch.num_rows
            h, c = np.unique(np.asarray(column.values)[off[0] : off[-1]], return_counts=True)
            if found is not None:
                h, where = np.unique(np.concatenate([found[0], h]), return_inverse=True)
                c = np.bincount(where, np.concatenate([found[1], c])).astype(np.int64)
            keep = c >= share * n / 2  # half the share so far: what is let go is too rare, or becomes rare
            found = h[keep], c[keep]
        if n:
            keep = found[1] >= max(2, share * n / 2)
            yield pa.RecordBatch.from_arrays([pa.array(found[0][keep]), pa.array(found[1][keep].astype(np.int64))], names=["h", "c"])
        give_back()

    found = sets.select("hashes").mapInArrow(run, "h bigint, c bigint").groupBy("h").agg(F.sum("c").alias("c")).filter(F.col("c") >= max(4, share * n_sets))
    return np.sort(np.array([r["h"] for r in found.select("h").collect()], np.int64).view(np.uint64))


# ---------------------------------------------------------------- DivideSkip
def merge_skip(lists: list[list[int]], need: int) -> list[tuple[int, int]]:
    """(member, occurrences) of those in at least `need` of these sorted lists, by a heap of the lists' heads.

    Where the least head occurs too rarely, the need - 1 least heads are popped at once: no member before the next head
    can reach `need`, so their lists jump there by binary search.
    """
    heap = [(x[0], k) for k, x in enumerate(lists) if x]
    heapq.heapify(heap)
    at, out, pop, push = [0] * len(lists), [], heapq.heappop, heapq.heappush
    while len(heap) >= need:
        low, popped = heap[0][0], []
        while heap and heap[0][0] == low:
            popped.append(pop(heap)[1])
        if len(popped) >= need:
            out.append((low, len(popped)))
            for k in popped:
                at[k] += 1
                if at[k] < len(lists[k]):
                    push(heap, (lists[k][at[k]], k))
            continue
        while heap and len(popped) < need - 1:
            popped.append(pop(heap)[1])
        if not heap:
            break
        goal = heap[0][0]
        for k in popped:
            at[k] = bisect_left(lists[k], goal, at[k])
            if at[k] < len(lists[k]):
                push(heap, (lists[k][at[k]], k))
    return out


def merge_runs(members: np.ndarray, need: int) -> list[tuple[int, int]]:
    """What `merge_skip` gives, for the lists' concatenation: one merge of all runs and counts of equal neighbours."""
    found, count = np.unique(members, return_counts=True)
    keep = count >= need
    return list(zip(found[keep].tolist(), count[keep].tolist(), strict=True))


def n_set_aside(t: int, longest: int) -> int:
    """Number of long lists that are not merged: the rule of DivideSkip with its usual constant."""
    return min(t - 1, int(t / (0.0085 * np.log2(max(2, longest)) + 1)))


def overlapping(posting: np.ndarray, low: np.ndarray, high: np.ndarray, found: list[tuple[int, int]], sizes: np.ndarray, size: int, pct: int) -> list[int]:
    """Members of `found` (member, occurrences so far) that overlap enough with a set of `size` once they are looked up
    in the long lists posting[low:high]. Each list is searched for all members that can still get there."""
    member = np.array([j for j, _ in found], np.int64)
    count = np.array([c for _, c in found], np.int64)
    needed = -(-pct * (size + sizes[member]) // (100 + pct))
    left = len(low)
    for a, b in zip(low.tolist(), high.tolist(), strict=True):
        possible = count + left >= needed
        if not possible.all():
            member, count, needed = member[possible], count[possible], needed[possible]
        if not len(member):
            return []
        run = posting[a:b]
        at = np.searchsorted(run, member)
        count += run[np.minimum(at, b - a - 1)] == member
        left -= 1
    return member[count >= needed].tolist()


def search(sets: list[np.ndarray], pct: int, component: np.ndarray, probe: np.ndarray) -> tuple[list[tuple[int, int]], dict[str, int]]:
    """(links (i, j) that merge different components, among sets of which one at least is a probe; the work done)."""
    n = len(sets)
    sizes = np.array([len(s) for s in sets])
    order = np.argsort(sizes, kind="stable")
    sizes = sizes[order]
    off = np.concatenate([[0], np.cumsum(sizes)])
    flat = np.concatenate([sets[i] for i in order])
    by = np.argsort(flat, kind="stable")  # owners stay ascending within a hash
    posting, hashes = np.repeat(np.arange(n, dtype=np.int32), sizes)[by], flat[by]
    first = np.flatnonzero(np.concatenate([[True], hashes[1:] != hashes[:-1]]))
    ends = np.append(first[1:], len(hashes))
    list_end = np.repeat(ends, ends - first)
    place = np.empty(len(by), np.int64)
    place[by] = np.arange(len(by))  # where each set's own entries are; later members of a list stand behind them
    del flat, hashes, by, first, ends
    label, is_probe = component[order].copy(), probe[order]
    out, work = [], {"merged": 0, "set_aside": 0, "found": 0, "by_heap": 0, "by_runs": 0}
    for q in range(n):
        size = int(sizes[q])
        upto = int(np.searchsorted(sizes, 100 * size // pct, side="right"))
        if upto <= q + 1 or (label[q + 1 : upto] == label[q]).all():
            continue
        t = -(-2 * pct * size // (100 + pct))
        low = place[off[q] : off[q + 1]] + 1
        high = list_end[low - 1]
        some = high > low
        if some.sum() < t:
            continue
        low, high = low[some], high[some]
        length = high - low
        rank = np.argsort(length, kind="stable")
        n_long = n_set_aside(t, int(length[rank[-1]]))
        short, long, need = rank[: len(rank) - n_long], rank[len(rank) - n_long :], t - n_long
        lens = length[short]
        cut = np.cumsum(lens)
        members = posting[np.repeat(low[short] - (cut - lens), lens) + np.arange(cut[-1])]
        use = (members < upto) & (label[members] != label[q])
        if not is_probe[q]:
            use &= is_probe[members]
        left = np.add.reduceat(use, cut - lens)
        if (left > 0).sum() < need:
            continue
        members = members[use]
        if len(members) <= HEAP_POSTINGS:
            lists = members.tolist()
            found = merge_skip([lists[a:b] for a, b in pairwise(accumulate(left.tolist(), initial=0)) if b > a], need)
            work["by_heap"] += 1
        else:
            found = merge_runs(members, need)
            work["by_runs"] += 1
        work["merged"] += len(members)
        work["set_aside"] += int(length[long].sum())
        work["found"] += len(found)
        for j in overlapping(posting, low[long], high[long], found, sizes, size, pct):
            if label[j] != label[q]:
                out.append((int(order[q]), int(order[j])))
                label[label == label[j]] = label[q]
    return out, work


def _search_groups(rows: DataFrame, keys: list[str], pct: int) -> DataFrame:
    """(a, b) within groups of (rid, hashes, component, probe): the links, as stars round the least rid of each new
    component of a group."""

    def run(table: pa.Table) -> pa.Table:
        rids, at = np.unique(table.column("rid").to_numpy(), return_index=True)
        if len(rids) < 2:
            return pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64())})
        column = table.combine_chunks().column("hashes").chunk(0)
        flat, off = np.asarray(column.values), np.asarray(column.offsets)
        sets = [np.sort(flat[off[k] : off[k + 1]]) for k in at]
        links, _ = search(sets, pct, table.column("component").to_numpy()[at], np.asarray(table.column("probe"))[at])
        root: dict[int, int] = {}

        def find(x: int) -> int:
            while (up := root.get(x, x)) != x:
                root[x] = root.get(up, up)
                x = up
            return x

        for i, j in links:
            i, j = find(i), find(j)
            root[max(i, j)] = min(i, j)
        a = sorted({x for link in links for x in link})
        a, b = rids[np.array(a, np.int64)], rids[np.array([find(x) for x in a], np.int64)]
        if table.nbytes > 1 << 20:
            give_back()
        return pa.table({"a": pa.array(a[a != b]), "b": pa.array(b[a != b])})

    return rows.select(*keys, "rid", "hashes", "component", "probe").groupBy(*keys).applyInArrow(run, "a bigint, b bigint")


# ---------------------------------------------------------------- the join
def n_passes(hashes: int, total: int, least: int) -> int:
    """Passes for so many hashes, where each has an eighth of `total` or `least`, whichever is more."""
    return 1 + hashes // max(least, total // 8)


def one_pass(rows: DataFrame, at: int, passes: int, *keys: str) -> DataFrame:
    """The rows whose keys belong to this pass."""
    return rows if passes == 1 else rows.filter(F.pmod(F.xxhash64(*keys), F.lit(passes)) == at)


def _candidates(base: DataFrame, pct: int, sample_hashes: int = 1_000_000, heavy_hits: int = 50, pass_hashes: int = PASS_HASHES) -> DataFrame:
    """rid of the classes that pass the first T-occurrence test (step 2), counted in passes over the range of hashes."""
    scratch = Scratch(base.sparkSession)
    total = base.agg(F.sum(F.size("hashes"))).first()[0] or 0
    share = min(1.0, sample_hashes / max(1, total))
    heavy = base.filter(F.pmod(F.xxhash64("cid"), F.lit(1 << 30)) < int(share * (1 << 30))).select("cid", F.explode("hashes").alias("h")).distinct()
    heavy = scratch.save(heavy.groupBy("h").agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") >= heavy_hits).select("h", F.lit(True).alias("heavy")), "heavy")
    passes = n_passes(total, total, pass_hashes)

    def hits(at: int) -> DataFrame:
        mine = F.col("hashes") if passes == 1 else F.filter("hashes", lambda h: F.pmod(h, F.lit(passes)) == at)
        classes = base.filter("cid is not null").withColumn("hashes", mine).groupBy("cid").agg(F.min("rid").alias("rid"), F.first("n").alias("n"), F.first("hashes").alias("hashes"))
        rows = classes.select("rid", "n", F.explode("hashes").alias("h")).join(F.broadcast(heavy), "h", "left")
        rows = rows.select("rid", "n", "h", F.coalesce("heavy", F.lit(False)).alias("heavy")).withColumn("salt", F.when(F.col("heavy"), F.col("rid")).otherwise(F.lit(0)))
        hit = rows.withColumn("c", F.count(F.lit(1)).over(Window.partitionBy("h", "salt"))).filter("heavy or c > 1")
        return hit.groupBy("rid").agg(F.count(F.lit(1)).alias("hits"), F.first("n").alias("n"))

    found = scratch.save_each(map(hits, range(passes)), "hits")
    need = F.greatest(F.lit(1), F.least(F.expr(f"({100 - pct} * n) div 200"), F.expr(f"({pct} * n + 99) div 100")) - 1)
    out = scratch.save(found.groupBy("rid").agg(F.sum("hits").alias("hits"), F.first("n").alias("n")).filter(F.col("hits") >= need).select("rid"), "candidates")
    scratch.drop(heavy, found)
    return out


def _stars(parts: DataFrame, scratch: Scratch, passes: int) -> DataFrame:
    """(a, b): a class and the least class b that has one of its parts, if that is another one; a pair may be repeated."""

    def star(at: int) -> DataFrame:
        mine = one_pass(parts, at, passes, "s")
        leaders = scratch.save(mine.groupBy("s").agg(F.min("rid").alias("b"), F.count(F.lit(1)).alias("c")).filter("c > 1").select("s", "b"), "leaders")
        given.append(leaders)
        return mine.join(leaders, "s").filter("rid <> b").select(F.col("rid").alias("a"), "b").distinct()

    given: list[DataFrame] = []
    out = scratch.save_each(map(star, range(passes)), "stars")
    scratch.drop(*given)
    return out


def _placed(members: DataFrame, scratch: Scratch, chunk_hashes: int) -> DataFrame:
    """(rid, n, block, chunks, chunk) of (rid, block, n)."""
    sized = members.groupBy("block").agg(F.sum("n").alias("total")).withColumn("chunks", F.ceil(F.col("total") / chunk_hashes).cast("int"))
    chunk = F.pmod(F.xxhash64("rid"), F.col("chunks")).cast("int")
    return scratch.save(spread_join(members, sized.select("block", "chunks"), "block", "rid").select("rid", "n", "block", "chunks", chunk.alias("chunk")), "placed")


def _groups(placed: DataFrame, stars: DataFrame, few, scratch: Scratch, chunk_hashes: int) -> DataFrame:
    """`placed` with blocks over one chunk replaced by the groups round their least classes (step 3)."""
    wide = scratch.save(placed.filter("chunks > 1").select("rid", "n"), "wide")
    n_wide = wide.count()
    if not n_wide:
        scratch.drop(wide)
        return placed
    pairs = stars.join(few(wide.select(F.col("rid").alias("a")), n_wide), "a", "left_semi")
    groups = pairs.select(F.col("a").alias("rid"), F.col("b").alias("block")).union(pairs.select(F.col("b").alias("rid"), F.col("b").alias("block"))).distinct()
    groups = scratch.save(groups.join(few(wide, n_wide), "rid"), "groups")
    again = _placed(groups, scratch, chunk_hashes)
    out = scratch.save_each([placed.filter("chunks = 1"), again], "placed")
    scratch.drop(wide, groups, again, placed)
    return out


def class_links(docs: DataFrame, k: int, pct: int, scratch: Scratch, chunk_hashes: int = 800_000, broadcast_rows: int = 1_000_000, pass_hashes: int = PASS_HASHES) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(rows (doc_id, cid, n) of all documents, classes (cid, rid, doc_id) with the least doc_id, components (a, b) of
    rids)."""
    spark = docs.sparkSession
    few = lambda df, n: F.broadcast(df) if n <= broadcast_rows else df
    base = scratch.save(set_rows(docs, k, pct, whole=False).withColumn("rid", F.monotonically_increasing_id()), "base")
    rows = scratch.save(base.select("doc_id", "cid", "n"), "rows")
    classes = scratch.save(base.filter("cid is not null").groupBy("cid").agg(F.min("rid").alias("rid"), F.min("doc_id").alias("doc_id"), F.first("n").alias("n")), "classes")
    candidates = _candidates(base, pct, pass_hashes=pass_hashes)
    scratch.drop(base)
    n_kept = candidates.count()
    nothing = spark.createDataFrame([], "a bigint, b bigint")
    if not n_kept:
        return rows, classes, nothing
    kept = scratch.save(classes.join(few(candidates, n_kept), "rid", "left_semi"), "kept")
    scratch.drop(candidates)
    top, n_hashes = kept.agg(F.max("n"), F.sum("n")).first()
    passes = n_passes(n_hashes, n_hashes, pass_hashes)

    def whole(at: int) -> DataFrame:
        """The texts of the candidates again, now for their whole sets."""
        names = one_pass(kept, at, passes, "doc_id")
        ids = few(names.select(F.col("doc_id").alias("__rc_id")).distinct(), n_kept // passes)
        texts = one_pass(docs, at, passes, "doc_id").select("doc_id", "text").join(ids, F.col("doc_id").eqNullSafe(F.col("__rc_id")), "left_semi")
        return set_rows(texts, k, pct, whole=True).select("cid", "hashes").join(few(names.select("cid", "rid"), n_kept // passes), "cid").select("rid", "hashes")

    sets = scratch.save_each(map(whole, range(passes)), "sets")
    if sets.count() > n_kept:  # a class whose doc_id has several rows, in several tasks
        again = scratch.save(sets.groupBy("rid").agg(F.first("hashes").alias("hashes")), "sets")
        scratch.drop(sets)
        sets = again

    edges_of_bands = bands(pct, top)
    common = spark.sparkContext.broadcast(common_hashes(sets, n_kept, n_hashes))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            column = batch.column(1)
            flat, off = np.asarray(column.values), np.asarray(column.offsets)
            found = [signatures(np.sort(flat[a:b].view(np.uint64)), edges_of_bands, pct, common.value) for a, b in pairwise(off.tolist())]
            yield pa.RecordBatch.from_arrays([batch.column(0), list_column(found)], names=["rid", "s"])
        give_back()

    parts = scratch.save(sets.mapInArrow(run, "rid bigint, s array<bigint>").select("rid", F.explode("s").alias("s")), "parts")
    stars = _stars(parts, scratch, passes)
    scratch.drop(parts)
    blocks = components(stars, scratch)
    members = blocks.select(F.col("a").alias("rid"), F.col("b").alias("block")).union(blocks.select(F.col("b").alias("rid"), F.col("b").alias("block")).distinct())
    members = scratch.save(members.join(few(kept.select("rid", "n"), n_kept), "rid"), "members")
    placed = _groups(_placed(members, scratch, chunk_hashes), stars, few, scratch, chunk_hashes)
    scratch.drop(members, blocks, stars)
    n_placed, hashes = placed.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first()
    turns = n_passes(hashes, n_hashes, pass_hashes)

    def with_sets(at: int, of: DataFrame) -> DataFrame:
        return sets.join(few(one_pass(of, at, turns, "block").drop("n"), n_placed // turns), "rid")

    def searched(at: int) -> DataFrame:
        return _search_groups(with_sets(at, placed).withColumn("component", F.col("rid")).withColumn("probe", F.lit(True)), ["block", "chunk"], pct)

    links = scratch.save_each(map(searched, range(turns)), "links")
    if not placed.filter("chunks > 1").limit(1).count():
        scratch.drop(placed, sets, kept)
        return rows, classes, links
    large = scratch.save_each((with_sets(at, placed.filter("chunks > 1")).select("block", "chunk", "chunks", "rid", "hashes") for at in range(turns)), "large")
    scratch.drop(sets)
    found = components(_across_chunks(large, links, pct, scratch, chunk_hashes, max(pass_hashes, n_hashes // 8)), scratch)
    scratch.drop(placed, large, links, kept)
    return rows, classes, found


def _with_component(rows: DataFrame, found: DataFrame) -> DataFrame:
    return rows.join(found.select(F.col("a").alias("rid"), F.col("b").alias("__rc_c")), "rid", "left").withColumn("component", F.coalesce("__rc_c", "rid")).drop("__rc_c")


def _across_chunks(large: DataFrame, links: DataFrame, pct: int, scratch: Scratch, chunk_hashes: int, pass_hashes: int) -> DataFrame:
    """All links, those across chunks of one block included (step 4). A class may be in several blocks."""
    rows = _with_component(large, components(links, scratch))
    # one member of each component in each chunk, searched together
    one = rows.groupBy("block", "chunk", "component").agg(F.min("rid").alias("rid"))
    one = scratch.save(rows.drop("component").join(one.select("block", "rid", "component"), ["block", "rid"]), "one")
    share = scratch.save(one.groupBy("block").agg(F.ceil(F.sum(F.size("hashes")) / chunk_hashes).cast("int").alias("cuts")), "share")
    one = one.join(share, "block").withColumn("cut", F.pmod(F.xxhash64("component"), F.col("cuts"))).withColumn("probe", F.lit(True))
    links = scratch.save(links.union(_search_groups(one, ["block", "cut"], pct)), "links")
    # those outside the block's largest component, against every chunk
    rows = scratch.save(_with_component(large, components(links, scratch)), "outside")
    counts = rows.groupBy("block", "component").agg(F.count(F.lit(1)).alias("c"))
    main = scratch.save(counts.groupBy("block").agg(F.max_by("component", F.struct("c", "component")).alias("main")), "main")
    outside = scratch.save(rows.join(main, "block").filter("component <> main").drop("main"), "outside")
    width = scratch.save(outside.groupBy("block").agg(F.ceil(F.sum(F.size("hashes")) / chunk_hashes).cast("int").alias("cuts")), "width")
    indexed = rows.join(width, "block").withColumn("cut", F.explode(F.sequence(F.lit(0), F.col("cuts") - 1))).withColumn("probe", F.lit(False))
    probes = outside.join(width, "block").withColumn("cut", F.pmod(F.xxhash64("rid"), F.col("cuts")).cast("int")).withColumn("chunk", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1))).withColumn("probe", F.lit(True))
    columns = ["block", "chunk", "cut", "rid", "hashes", "component", "probe"]
    both = probes.select(*columns).union(indexed.select(*columns))
    # each probe meets every chunk, and each chunk every cut of the probes: more hashes than the block has, by far
    many = outside.select("block", F.size("hashes") * F.col("chunks")).union(rows.join(width, "block").select("block", F.size("hashes") * F.col("cuts"))).toDF("block", "c")
    passes = n_passes(many.agg(F.coalesce(F.sum("c"), F.lit(0))).first()[0], 0, pass_hashes)

    def searched(at: int) -> DataFrame:
        # a probe that is also in the chunk's index counts once, as a probe
        mine = one_pass(both, at, passes, "block", "chunk", "cut").groupBy("block", "chunk", "cut", "rid").agg(F.max("probe").alias("probe"), F.first("hashes").alias("hashes"), F.first("component").alias("component"))
        return _search_groups(mine, ["block", "chunk", "cut"], pct)

    across = scratch.save_each(map(searched, range(passes)), "across")
    return links.union(across)


def class_roots(classes: DataFrame, found: DataFrame) -> DataFrame:
    """(cid, component_id): the least doc_id of each class's component."""
    ids = _with_component(classes.select("cid", "rid", "doc_id"), found)
    roots = ids.groupBy("component").agg(F.min("doc_id").alias("component_id"))
    return spread_join(ids, roots, "component", "rid").select("cid", "component_id")


def components_of(docs: DataFrame, k: int = 3, pct: int = 90, chunk_hashes: int = 800_000, pass_hashes: int = PASS_HASHES) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every document."""
    scratch = Scratch(docs.sparkSession)
    rows, classes, found = class_links(docs, k, pct, scratch, chunk_hashes, pass_hashes=pass_hashes)
    with_set = rows.filter("cid is not null").join(class_roots(classes, found), "cid").select("doc_id", F.col("n").cast("long").alias("n_shingles"), "component_id")
    without = rows.filter("cid is null").select("doc_id", F.lit(0).cast("long").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    return with_set.union(without)


def keep_one(docs: DataFrame, k: int = 5, pct: int = 80, broadcast_rows: int = 500_000) -> DataFrame:
    """One row of each component, with all columns: that with the least doc_id, then with the least digest of its text;
    one without a doc_id only where no other has one. Rows without words stay.

    A row is named by its doc_id and the digest of its text, so texts that share a doc_id, or have none, go or stay each
    by itself. Repeats of one (doc_id, text) become one row; those without words and doc_id stay.
    """
    scratch = Scratch(docs.sparkSession)
    digest = F.unhex(F.md5(F.col("text").cast("binary")))
    name = F.struct(F.col("doc_id").isNull().alias("last"), F.col("doc_id").alias("id"), digest.alias("digest"))
    rows, classes, found = class_links(docs.select(name.alias("doc_id"), "text"), k, pct, scratch)
    roots = class_roots(classes, found)

    def named(names: DataFrame, what: str) -> tuple[DataFrame, Column, int]:
        """The written names, by broadcast where they are few; the condition of a join with them; their number."""
        names = scratch.save(names.select(F.col("doc_id.id").alias("__rc_id"), F.col("doc_id.digest").alias("__rc_digest")), what)
        n = names.count()
        return F.broadcast(names) if n <= broadcast_rows else names, F.col("doc_id").eqNullSafe(F.col("__rc_id")) & digest.eqNullSafe(F.col("__rc_digest")), n

    losers, same, _ = named(rows.filter("cid is not null").join(roots, "cid").filter("doc_id <> component_id").select("doc_id").distinct(), "losers")
    repeated = rows.filter("cid is not null or not doc_id.last").groupBy("doc_id").agg(F.count(F.lit(1)).alias("c")).filter("c > 1")
    twice, again, n_twice = named(repeated, "twice")
    scratch.drop(rows, classes)
    kept = docs.join(losers, same, "left_anti")
    if not n_twice:
        return kept
    return kept.join(twice, again, "left_anti").union(kept.join(twice, again, "left_semi").dropDuplicates(["doc_id", "text"]))
