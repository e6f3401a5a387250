"""Token counts that follow edits: a segment tree over the pre-tokens of each document.

A leaf is a run of LEAF pre-token chunks (characters without white space) and the white space after each; it holds its
number of characters and of tokens, and inner nodes hold sums. An edit is found by descent over character sums. Only the leaves that it touches
and one leaf on each side (the boundary context: no token reaches across white space) are encoded again, and the sums
above them are updated. Leaves merged by an edit become one leaf, the others empty, so the tree keeps its shape.

`build` makes the table of trees: per document the text and its leaves' characters and tokens (inner nodes are sums of
them, made when a tree is read). `recount` reads that table and the edits, encodes the touched leaves only, and gives the
trees after the edits beside the counts, so that a later round of edits starts from them and no text is encoded twice.

Defined cases: null text is the empty text; edits outside the text are clipped to it; null replacement is the empty
string; edits apply in order, each to the text that the ones before left; a document without edits keeps its count;
repeated rows are counted one by one; extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from regioncount.llm.common import slices
from regioncount.llm.op5_bpe import CACHE_ENTRIES, Vocabulary, encoder_path


#: Chunks of a leaf.
LEAF = 2


class TokenTree:
    """Counts of one document, made of its leaves' known numbers of characters and tokens; nothing is encoded.

    `count` gives the tokens of a string without white space inside tokens; edits call it for what they touch.
    """

    def __init__(self, text: str, chars, tokens, count):
        self.count, self.original, self.encoded = count, text, 0
        self.n_leaves = max(1, len(chars))
        self.begin = [0, *np.cumsum(chars).tolist()] if len(chars) else [0, 0]
        self.changed: dict[int, str] = {}
        self.size = 1 << (self.n_leaves - 1).bit_length()
        self.chars, self.tokens = self._sums(chars), self._sums(tokens)

    def _sums(self, values) -> list[int]:
        """The tree as a list: node k above nodes 2 k and 2 k + 1, leaves from `size` on."""
        out = np.zeros(2 * self.size, np.int64)
        out[self.size : self.size + len(values)] = values
        at = self.size
        while at > 1:
            out[at // 2 : at] = out[at : 2 * at : 2] + out[at + 1 : 2 * at : 2]
            at //= 2
        return out.tolist()

    def leaf(self, k: int) -> str:
        found = self.changed.get(k)
        return self.original[self.begin[k] : self.begin[k + 1]] if found is None else found

    @property
    def total(self) -> int:
        return self.tokens[1]

    @property
    def length(self) -> int:
        return self.chars[1]

    def find(self, at: int) -> tuple[int, int]:
        """(leaf, offset in it) of a character; the last non-empty leaf for the end of the text."""
        at, k = min(at, max(0, self.length - 1)), 1
        while k < self.size:
            k *= 2
            if at >= self.chars[k] and self.chars[k + 1]:
                at -= self.chars[k]
                k += 1
        return k - self.size, at

    def _set(self, leaf: int, text: str) -> None:
        self.changed[leaf] = text
        k = self.size + leaf
        self.chars[k], self.tokens[k] = len(text), self.count(text) if text else 0
        while k > 1:
            k //= 2
            self.chars[k] = self.chars[2 * k] + self.chars[2 * k + 1]
            self.tokens[k] = self.tokens[2 * k] + self.tokens[2 * k + 1]

    def before(self, leaf: int) -> int:
        """Characters before a leaf."""
        k, out = self.size + leaf, 0
        while k > 1:
            if k % 2:
                out += self.chars[k - 1]
            k //= 2
        return out

    def edit(self, start: int, end: int, replacement: str) -> None:
        """Replace characters start..end-1, clipped to the text."""
        start = min(max(0, start), self.length)
        end = min(max(start, end), self.length)
        if not self.length:
            self._set(0, replacement)
            self.encoded += 1
            return
        first, last = self.find(start)[0], self.find(max(start, end - 1))[0]
        begin = self.before(first)
        if begin:
            first = self.find(begin - 1)[0]
            begin = self.before(first)
        stop = self.before(last) + self.chars[self.size + last]
        if stop < self.length:
            last = self.find(stop)[0]
        touched = [k for k in range(first, last + 1) if self.chars[self.size + k]]
        text = "".join(map(self.leaf, touched))
        self.encoded += len(touched)
        for k in touched:
            if k != first:
                self._set(k, "")
        self._set(first, text[: start - begin] + replacement + text[end - begin :])

    def text(self) -> str:
        out, at = [], 0
        for k in sorted(self.changed):
            out += [self.original[at : self.begin[k]], self.changed[k]]
            at = self.begin[k + 1]
        return "".join([*out, self.original[at:]])


def leaf_splitter():
    """Function that cuts a text into leaves of LEAF chunks."""
    import regex

    return regex.compile(rf"\s*+(?:\S++\s*+){{1,{LEAF}}}+|\s++").findall


class Counter:
    """Tokens of texts, with a bounded memory of their chunks."""

    def __init__(self, enc):
        self.split, self.cut = enc.split, leaf_splitter()
        self.seen = enc.remember(len, sum, 3 * CACHE_ENTRIES, CACHE_ENTRIES)

    def chunks(self, text: str) -> list[int]:
        get, miss = self.seen.get, self.seen.miss
        return [get(c) or miss(c) for c in self.split(text)]

    def count(self, text: str) -> int:
        return sum(self.chunks(text))

    def leaves(self, text: str) -> tuple[list[int], list[int]]:
        """Characters and tokens of each leaf; a text of white space alone is one leaf without tokens."""
        n = self.chunks(text)
        chars = list(map(len, self.cut(text)))
        return chars, [sum(n[k : k + LEAF]) for k in range(0, len(n), LEAF)] or [0] * len(chars)


def _lists(values: list) -> pa.ListArray:
    offsets = np.cumsum([0, *map(len, values)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array([x for v in values for x in v], pa.int32()))


def _rows(column: pa.ListArray) -> list[np.ndarray]:
    """The lists of a column; null counts as empty."""
    flat, sizes = column.flatten().to_numpy(zero_copy_only=False), column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    return np.split(flat, np.cumsum(sizes)[:-1]) if len(sizes) else []


def build(docs: DataFrame, path: str | None = None) -> DataFrame:
    """The trees (doc_id, text, chars, tokens) of every whole text: characters and tokens of its leaves, in text order."""
    shared = docs.sparkSession.sparkContext.broadcast(Vocabulary(path or encoder_path()))
    docs = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = shared.value.encoder()
        counter = Counter(enc)
        for batch in slices(batches):
            found = [counter.leaves(x.as_py()) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), _lists([x[0] for x in found]), _lists([x[1] for x in found])], names=["doc_id", "text", "chars", "tokens"])
        enc.forget()

    return docs.mapInArrow(run, f"doc_id {kind}, text string, chars array<int>, tokens array<int>")


def recount(trees: DataFrame, path: str | None = None, keep_trees: bool = True) -> DataFrame:
    """(doc_id, n_before, n_tokens, n_edits, n_leaves, n_encoded) of every tree, and the trees after the edits.

    `edits`, beside the columns of `build`, is an array of (start, end, replacement) in code points. Only touched
    leaves are encoded (n_encoded of them); without `keep_trees` the columns text, chars and tokens stay away.
    """
    shared = trees.sparkSession.sparkContext.broadcast(Vocabulary(path or encoder_path()))
    trees = trees.select("doc_id", "text", "chars", "tokens", "edits")
    kind = trees.schema["doc_id"].dataType.simpleString()
    names = ["n_before", "n_tokens", "n_edits", "n_leaves", "n_encoded"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = shared.value.encoder()
        count = Counter(enc).count
        for batch in slices(batches):
            out, texts, chars, tokens = [], [], [], []
            for text, c, n, edits in zip(batch.column(1), _rows(batch.column(2)), _rows(batch.column(3)), batch.column(4).to_pylist(), strict=True):
                tree = TokenTree(text.as_py() or "", c, n, count)
                before = tree.total
                for e in edits or []:
                    tree.edit(e["start"], e["end"], e["replacement"] or "")
                if keep_trees:
                    leaves = [(x, y) for x, y in zip(tree.chars[tree.size :], tree.tokens[tree.size :], strict=True) if x]
                    texts.append(tree.text())
                    chars.append([x for x, _ in leaves])
                    tokens.append([y for _, y in leaves])
                out.append((before, tree.total, len(edits or []), tree.n_leaves if tree.length else 0, tree.encoded))
            columns = zip(*out, strict=True) if out else [[] for _ in names]
            arrays = [batch.column(0), *[pa.array(c, pa.int64()) for c in columns]]
            held = [pa.array(texts, pa.string()), _lists(chars), _lists(tokens)] if keep_trees else []
            yield pa.RecordBatch.from_arrays([*arrays, *held], names=["doc_id", *names, *(["text", "chars", "tokens"] if keep_trees else [])])
        enc.forget()

    return trees.mapInArrow(run, f"doc_id {kind}, " + ", ".join(f"{n} long" for n in names) + (", text string, chars array<int>, tokens array<int>" if keep_trees else ""))


def sample_edits(text: Column) -> Column:
    """Three edits that follow from the text's length: a replacement, an insertion inside a word, a deletion."""
    n = F.char_length(F.coalesce(text, F.lit("")))
    one = lambda a, b, r: F.struct(a.cast("int").alias("start"), b.cast("int").alias("end"), F.lit(r).alias("replacement"))
    third, half = F.floor(n / 3), F.floor(n / 2)
    return F.array(one(third, third + 7, " edited span 42 "), one(half, half, "x"), one(2 * third, 2 * third + 5, ""))
