"""Jaccard join, byte-pair encoding, token counts and the pipeline against brute force."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from regioncount.llm import op4_jaccard as j
from regioncount.llm import op5_bpe as b
from regioncount.llm import op6_tokens as k
from regioncount.llm.common import Recent, Scratch
from regioncount.llm.components import components


def brute_sets(text, size):
    w = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "").encode().split()
    return {tuple(w[i : i + size]) for i in range(len(w) - size + 1)} if len(w) >= size else ({tuple(w)} if w else set())


def brute_components(rows, size, pct):
    sets, root = [brute_sets(t, size) for _, t in rows], list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for c in range(a):
            both = len(sets[a] & sets[c])
            if sets[a] and sets[c] and 100 * both >= pct * (len(sets[a]) + len(sets[c]) - both):
                root[find(a)] = find(c)
    least = {}
    for a, (i, _) in enumerate(rows):
        if i is not None:
            least[find(a)] = min(i, least.get(find(a), i))
    return sorted((str(rows[a][0]), len(sets[a]), str(least.get(find(a)))) for a in range(len(rows)))


def near_copies(seed):
    rng, vocab, rows = random.Random(seed), [f"w{i}" for i in range(300)], []
    passage = [rng.choice(vocab) for _ in range(50)]
    bases = [[rng.choice(vocab) for _ in range(rng.choice([1, 2, 4, 12, 40, 120]))] for _ in range(25)] + [passage + [rng.choice(vocab) for _ in range(25)] for _ in range(15)]
    for base in bases:
        for _ in range(rng.choice([1, 2, 7])):
            w = list(base)
            for _ in range(rng.choice([0, 1, 2, 4])):
                w[rng.randrange(len(w))] = rng.choice(vocab)
            rows.append((len(rows), " ".join(w)))
    return rows


@pytest.mark.parametrize("size,pct,chunk", [(3, 90, 800_000), (5, 80, 300)])
def test_components_against_brute_force(spark, size, pct, chunk):
    rows = near_copies(7)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((str(r.doc_id), r.n_shingles, str(r.component_id)) for r in j.components_of(df, size, pct, chunk_hashes=chunk).collect())
    assert got == brute_components(rows, size, pct)


@pytest.mark.parametrize("chunk", [800_000, 300])
def test_components_in_passes(spark, chunk):
    rows = near_copies(8)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((str(r.doc_id), r.n_shingles, str(r.component_id)) for r in j.components_of(df, 5, 80, chunk_hashes=chunk, pass_hashes=20_000).collect())
    assert got == brute_components(rows, 5, 80)


def test_search_reads_few_rows_of_chained_texts(spark, monkeypatch):
    """Short texts that share lines chain into one block, which is not searched all against all."""
    rng = random.Random(5)
    lines = [" ".join(f"w{rng.randrange(10**6)}" for _ in range(9)) for _ in range(302)]
    rows = [(i, " ".join(lines[i : i + 3])) for i in range(300)]
    rows[200] = (200, rows[100][1] + " more")
    read, search = [], j._search_groups
    monkeypatch.setattr(j, "_search_groups", lambda rows, keys, pct: read.append(rows.count()) or search(rows, keys, pct))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((str(r.doc_id), r.n_shingles, str(r.component_id)) for r in j.components_of(df, 3, 80, chunk_hashes=200).collect())
    assert got == brute_components(rows, 3, 80)
    assert 200 < sum(read) < 4 * len(rows)


def test_components_of_messy_rows(spark, messy, no_documents):
    rows = [(r.doc_id, r.text) for r in messy.collect()]
    got = sorted((str(r.doc_id), r.n_shingles, str(r.component_id)) for r in j.components_of(messy).collect())
    want = [(i, n, i if n == 0 else c) for i, n, c in brute_components(rows, 3, 90)]
    assert got == sorted(want) and j.components_of(no_documents).count() == 0


def test_keep_one(spark, messy):
    kept = j.keep_one(messy)
    assert kept.columns == messy.columns
    ids = sorted(str(r.doc_id) for r in kept.collect())
    assert ids == sorted(["1", "3", "4", "5", "6", "7", "8", "9", "10", "11", "None", "None"])


def test_keep_one_of_each_group_whatever_the_ids(spark):
    one, two, three = (" ".join(f"{c}{k}" for k in range(30)) for c in "abc")
    rows = [(5, one), (7, one), (5, two), (3, two), (None, two), (None, three), (None, three.upper()), (None, three), (None, None), (None, None), (9, ""), (8, "alone"), (8, "alone")]
    docs = spark.createDataFrame([(i, t, n) for n, (i, t) in enumerate(rows)], "doc_id long, text string, n_chars long")
    kept = j.keep_one(docs)
    left = [(r.doc_id, r.text if r.text is None else r.text.lower()) for r in kept.collect()]
    assert kept.columns == docs.columns
    assert sorted(left, key=str) == sorted([(5, one), (3, two), (None, three), (None, None), (None, None), (9, ""), (8, "alone")], key=str)


def test_heap_merge_with_skips_against_counting():
    rng = np.random.default_rng(1)
    for _ in range(300):
        lists = [np.unique(rng.integers(0, 60, rng.integers(1, 40))) for _ in range(rng.integers(1, 20))]
        t = int(rng.integers(1, len(lists) + 1))
        found, count = np.unique(np.concatenate(lists), return_counts=True)
        assert j.merge_skip([x.tolist() for x in lists], t) == [(x, c) for x, c in zip(found.tolist(), count.tolist(), strict=True) if c >= t]


def test_probes_of_long_lists():
    rng = np.random.default_rng(8)
    lists = [np.unique(rng.integers(0, 80, rng.integers(1, 60))) for _ in range(30)]
    ends = np.cumsum([len(x) for x in lists])
    posting, low, sizes = np.concatenate(lists), np.concatenate([[0], ends[:-1]]), rng.integers(10, 40, 80)
    for _ in range(50):
        found = [(m, int(rng.integers(0, 9))) for m in sorted(rng.choice(80, int(rng.integers(0, 30)), replace=False).tolist())]
        want = [m for m, c in found if 190 * (c + sum(m in x for x in lists)) >= 90 * (30 + sizes[m])]
        assert j.overlapping(posting, low, ends, found, sizes, 30, 90) == want


def test_search_merges_few_postings_and_misses_no_link():
    """A block of near copies of a few texts that share a passage: all found documents come from the heap, and the long
    lists, which hold most postings, are never merged."""
    rng = np.random.default_rng(3)
    shared = rng.integers(0, 2**60, 200)
    sets = []
    for _ in range(4):
        base = np.concatenate([shared, rng.integers(0, 2**60, 150)])
        for _ in range(40):
            x = base.copy()
            x[rng.integers(0, len(x), int(rng.integers(0, 25)))] = rng.integers(0, 2**60)
            sets.append(np.unique(x))
    n = len(sets)
    links, work = j.search(sets, 90, np.arange(n), np.ones(n, bool))
    want, got = np.arange(n), np.arange(n)
    for i in range(n):
        for k in range(i):
            both = len(np.intersect1d(sets[i], sets[k]))
            if 100 * both >= 90 * (len(sets[i]) + len(sets[k]) - both):
                want[want == want[i]] = want[k]
    for i, k in links:
        got[got == got[i]] = got[k]
    assert len(links) == n - len(set(want.tolist())) > 0
    assert len({(a, b) for a, b in zip(want.tolist(), got.tolist(), strict=True)}) == len(set(want.tolist())) == len(set(got.tolist()))
    assert work["found"] >= len(links) and 0 < 5 * work["merged"] < work["set_aside"] and work["by_heap"] > 10 * work["by_runs"]
    heap, j.HEAP_POSTINGS = j.HEAP_POSTINGS, 0
    try:
        again, work = j.search(sets, 90, np.arange(n), np.ones(n, bool))
    finally:
        j.HEAP_POSTINGS = heap
    assert again == links and work["by_heap"] == 0


def test_first_test_keeps_every_linked_class(spark):
    """With every frequent hash spread over tasks (a low bound) or none, the same classes pass."""
    rows = near_copies(12)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    base = j.set_rows(df, 3, 90, whole=False).withColumn("rid", F.monotonically_increasing_id()).cache()
    some = {r.rid for r in j._candidates(base, 90, heavy_hits=2).collect()}
    assert some == {r.rid for r in j._candidates(base, 90, heavy_hits=10**9).collect()} and 0 < len(some) < base.select("cid").distinct().count()


def test_partition_scheme_meets_every_link():
    rng = np.random.default_rng(2)
    for _ in range(300):
        pct, n = int(rng.choice([80, 90])), int(rng.integers(1, 200))
        a = np.unique(rng.integers(0, 2**63, n).astype(np.uint64))
        x, y = set(a.tolist()), set(a.tolist())
        while len(x & y) * 100 >= pct * len(x | y):
            last = set(y)
            y = set(y)
            if rng.random() < 0.5 and len(y) > 1:
                y.discard(next(iter(y)))
            else:
                y.add(int(rng.integers(0, 2**63)))
        y = last
        edges = j.bands(pct, 400)
        one, two = (j.signatures(np.array(sorted(s), np.uint64), edges, pct) for s in (x, y))
        assert len(np.intersect1d(one, two))
        for s, other in ((x, y), (y, x)):
            length, need = j.prefix_rule(len(s), pct)
            limit, _ = j.prefix_rule(len(other), pct)
            assert len(set(sorted(s)[:length]) & set(sorted(other)[:limit])) >= max(1, need - 1)


def test_connected_components(spark):
    rng = random.Random(3)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(150)] + [(k, k + 1) for k in range(300, 340)] + [(500, x) for x in range(501, 560)]
    root = {x: x for e in edges for x in e}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, c in edges:
        a, c = find(a), find(c)
        root[max(a, c)] = min(a, c)
    got = {r.a: r.b for r in components(spark.createDataFrame(edges, "a long, b long"), Scratch(spark)).collect()}
    assert got == {x: find(x) for x in root if find(x) != x}


def test_recent_remembers_frequent_keys():
    calls = []
    r = Recent(lambda key: calls.append(key) or len(key), 10)
    for step in range(200):
        assert r("often") == 5 and r(f"k{step}") == len(f"k{step}")
    assert calls.count("often") == 1 and len(r.young) + len(r.old) <= 20
    assert r("x" * 100) == 100 and "x" * 100 not in r.young


@pytest.fixture(scope="module")
def enc():
    return b.load()


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(b.encoder_path())


def test_ids_and_text_as_the_library(enc, library, sf_dir, spark):
    rng = random.Random(11)
    texts = [r.text for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()] + ["<|endoftext|> x<|startoftext|>Y's don't I'LL we've 12 34½ ²", "", "ΑΣ ΟΔΟΣ", "İstanbul ǅ", "a\x1cb\x85d　f", "日本語 テスト", "👍🏽 #hash!!", "x" * 5000]
    texts += ["".join(chr(rng.choice([rng.randint(1, 127), rng.randint(161, 0x24F), rng.randint(0x391, 0x3C9), rng.randint(0x1F300, 0x1F5FF)])) for _ in range(rng.randint(1, 25))) for _ in range(1500)]
    for x in texts:
        want = library.encode(x, add_special_tokens=False).ids
        ids = enc.encode(x)
        assert ids == want and enc.decode(ids) == library.decode(want, skip_special_tokens=False)


def test_random_strings_of_all_scripts_as_the_library(enc, library):
    """Code points that Python leaves unassigned and rare combining marks among them."""
    rng = random.Random(11)
    marks = "\u0558\u058c\u0c5c \n\x85\u2003\x1c\u200b'\u0130\u03a3\u1e9e"

    def one():
        r, c = rng.random(), rng.randint(0x80, 0x1FFFF)
        return chr(rng.randint(32, 126)) if r < 0.25 else rng.choice(marks) if r < 0.35 else chr(rng.randint(0x80, 0x2FFF)) if r < 0.65 else chr(rng.choice((rng.randint(0x300, 0x36F), rng.randint(0x8D0, 0x9FF), rng.randint(0x1100, 0x11FF)))) if r < 0.8 else "x" if 0xD800 <= c < 0xE000 else chr(c)

    for _ in range(20_000):
        text = "".join(one() for _ in range(rng.randint(0, 7)))
        want = library.encode(text, add_special_tokens=False)
        got = enc.encode(text)
        assert got == want.ids and enc.decode(got) == library.decode(want.ids, skip_special_tokens=False), text.encode("unicode_escape")


def test_words_and_chunks_by_the_short_ways(enc, library):
    """Chunks of Latin letters are split as by the file's steps; words of tokens in a row go back from dead prefixes."""
    rng = random.Random(7)
    letters = [c for c in map(chr, range(0xC0, 0x180)) if enc.latin(c)] + list("aZ'9s.-#%")
    for _ in range(3000):
        chunk = "".join(rng.choice(letters) for _ in range(rng.randint(1, 8)))
        assert enc.chunk_words(chunk) == enc.split_words(chunk)
    assert len(letters) > 150 and not enc.latin("\u0130") and not enc.latin("a b")
    plain = [t.removesuffix("</w>") for t in enc.vocab if t.removesuffix("</w>").isascii() and t.removesuffix("</w>").isalpha() and t == t.lower()]
    words = ["".join(rng.choice(plain) for _ in range(rng.randint(1, 9))) for _ in range(3000)] + ["ab" * 9999, "thethe" * 3000]
    for word in words:
        assert enc.word_ids(word) == library.encode(word, add_special_tokens=False).ids


def test_encode_keeps_few_chunks(enc):
    found = enc.remember(lambda ids: bytes(len(ids)), b"".join, b.FEW_ENTRIES)
    for k in range(3 * b.FEW_ENTRIES):
        found(f"w{k}")
    assert len(found.young) + len(found.old) <= 2 * b.FEW_ENTRIES
    enc.forget()
    assert not found.young and not found.old and len(enc.memories) == 2


def test_compatible_pairs_stay_themselves(enc):
    """Tokens side by side that fit encode to themselves; checked by merging step by step."""
    rank = {(x, y): r for r, (x, y) in enumerate(enc.merges)}

    def merge(parts):
        while True:
            found = [(rank[p], i) for i, p in enumerate(zip(parts, parts[1:], strict=False)) if p in rank]
            if not found:
                return parts
            i = min(found)[1]
            parts = parts[:i] + [parts[i] + parts[i + 1]] + parts[i + 2 :]

    rng = random.Random(5)
    plain = [t for t in enc.vocab if not t.endswith("</w>") and t.isalpha() and t.isascii()]
    for _ in range(1500):
        a, c = rng.choice(plain), rng.choice(plain)
        assert enc.compatible(enc.vocab[a], enc.vocab[c]) == (merge(list(a + c)) == [a, c])


def test_encoding_tables(spark, messy, no_documents, library):
    import hashlib

    rows = b.digests(messy).collect()
    texts = sorted(messy.collect(), key=lambda r: str(r))
    assert len(rows) == len(texts) and b.digests(no_documents).count() == 0
    want = set()
    for r in texts:
        ids = library.encode(r.text or "", add_special_tokens=False).ids
        want.add((r.doc_id, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    assert {tuple(r) for r in rows} == want
    encoded = b.encode(messy, keep=["doc_id", "lang"])
    back = {r.doc_id: r.decoded for r in b.decode(encoded).collect()}
    assert back[1] == "one</w> two</w> three</w> four</w> five</w> six</w> seven</w> .</w>" and back[4] == ""


def test_counts_after_edits(enc):
    import regex

    leaf = regex.compile(r"\s*+(?:\S++\s*+){1,3}+|\s++").findall
    count = lambda piece: sum(enc.cache(c)[0] for c in enc.split(piece))
    rng = random.Random(2)
    for _ in range(300):
        text = "".join(rng.choice("abc  \n'sé.9<|endoftext|>") for _ in range(rng.randint(0, 90)))
        tree = k.TokenTree(text, [len(x) for x in leaf(text)], [count(x) for x in leaf(text)], count)
        for _ in range(8):
            a = rng.randint(-2, len(text) + 2)
            c = rng.randint(a, a + 9)
            new = "".join(rng.choice("abc  \n'sé.9<|endoftext|>") for _ in range(rng.randint(0, 6)))
            tree.edit(a, c, new)
            a = min(max(0, a), len(text))
            text = text[:a] + new + text[min(max(a, c), len(text)) :]
            assert tree.text() == text and tree.total == len(enc.encode(text))


def test_edits_touch_few_leaves(enc):
    counter, text = k.Counter(enc), "some words here " * 5000
    tree = k.TokenTree(text, *counter.leaves(text), counter.count)
    tree.edit(40_000, 40_005, "new")
    assert tree.encoded <= 4 and tree.n_leaves > 1800


def edited(text, edits):
    for e in edits:
        a = min(max(0, e.start), len(text))
        text = text[:a] + (e.replacement or "") + text[min(max(a, e.end), len(text)) :]
    return text


def test_recount_table(spark, messy, no_documents, enc):
    trees = k.build(messy)
    trees = trees.withColumn("edits", k.sample_edits(trees["text"]))
    done = k.recount(trees)
    rows = {(r.doc_id, r.n_before, r.n_tokens, r.text) for r in done.collect()}
    edits = {r.text: r.edits for r in trees.collect()}
    want = set()
    for r in messy.collect():
        text = r.text or ""
        after = edited(text, edits[text])
        want.add((r.doc_id, len(enc.encode(text)), len(enc.encode(after)), after))
    assert rows == want
    # a second round starts from the trees of the first
    again = k.recount(done.withColumn("edits", k.sample_edits(done["text"])))
    for r in again.collect():
        assert r.n_tokens == sum(r.tokens) == len(enc.encode(r.text)) and sum(r.chars) == len(r.text)
    assert {(r.doc_id, r.n_before) for r in again.collect()} == {(i, n) for i, _, n, _ in rows}
    none = k.build(no_documents)
    assert k.recount(none.withColumn("edits", k.sample_edits(none["text"]))).count() == 0


def test_stored_counts_are_not_encoded_again(enc):
    text, counter, seen = "some words here " * 5000, k.Counter(enc), []

    def count(piece):
        seen.append(piece)
        return counter.count(piece)

    assert [k.Counter(enc).leaves(x) for x in ("", " \n ")] == [([], []), ([3], [0])]
    tree = k.TokenTree(text, *counter.leaves(text), count)
    assert not seen and tree.total == len(enc.encode(text))
    tree.edit(40_000, 40_005, "new")
    assert len(seen) <= 2 and sum(map(len, seen)) < 400 and tree.total == len(enc.encode(text[:40_000] + "new" + text[40_005:]))


def test_pipeline_stages_against_brute_force(spark, sf_dir):
    import corpus_pipeline as c
    from regioncount.llm import op3_toxicity, op9_decontamination, op10_pii

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    names = docs.columns
    out = c.toxicity(spark, docs, sf_dir)
    model = op3_toxicity.train(*op3_toxicity.labelled_sample(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))
    texts = docs.select("doc_id", "text").collect()
    scores = model.scorer().scores([r.text or "" for r in texts])
    assert out.columns == names and {r.doc_id for r in out.collect()} == {r.doc_id for r, x in zip(texts, scores, strict=True) if x < 0.5}
    one = c.near_duplicates(spark, docs, sf_dir)
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    assert one.columns == names and {str(r.doc_id) for r in one.collect()} == {i for i, n, comp in brute_components(rows, 5, 80) if n == 0 or i == comp}
    clean = c.decontamination(spark, docs, sf_dir)
    items = [brute_sets(r.text, 5) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    bad = {i for i, t in rows if any(q and len(q & brute_sets(t, 5)) >= 0.8 * len(q) - 1e-9 for q in items)}
    assert bad and clean.columns == names and {r.doc_id for r in clean.collect()} == {i for i, _ in rows} - bad
    assert op9_decontamination is not None
    masked = c.personal_data(spark, docs, sf_dir)
    weights = op10_pii.train()
    want = {r.doc_id: op10_pii.mask(r.text, op10_pii.all_spans(r.text, weights)[1]) for r in docs.collect()}
    assert masked.columns == names and {r.doc_id: r.text for r in masked.collect()} == want
    ids = c.tokens(spark, docs, sf_dir)
    enc = b.load()
    assert all(list(r.ids) == enc.encode(t) and r.n_tokens == len(r.ids) for r, t in zip(ids.orderBy("doc_id").collect(), [t for _, t in sorted(rows)], strict=True))


def test_pipeline_runs(spark, sf_dir):
    import corpus_pipeline as c

    out = c.run(spark, sf_dir)
    assert out.columns == ["doc_id", "lang", "source", "n_tokens", "ids"] and out.count() > 100


def test_written_tables_leave_no_shuffle_files(spark):
    """Files of a written table's shuffles go without waiting for the driver's own garbage."""
    import time

    tracker = spark._jvm.org.apache.spark.SparkEnv.get().mapOutputTracker()
    spark._jvm.System.gc()
    time.sleep(3)
    before, scratch = tracker.shuffleStatuses().size(), Scratch(spark)
    for k in range(12):
        scratch.save(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).agg(F.sum("id").alias(f"s{k}")), "sums")
    until = time.time() + 20
    while tracker.shuffleStatuses().size() > before + 2 and time.time() < until:
        time.sleep(0.2)
    assert tracker.shuffleStatuses().size() <= before + 2
    scratch.close()
