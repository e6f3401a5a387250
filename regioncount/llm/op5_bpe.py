"""Byte-pair encoding and decoding by a dynamic programme over prefixes, with the vocabulary files of public tokenizers.

For every prefix of a word there is exactly one token that can end its encoding. A token that starts at position j fits
if it is compatible with the token stored for prefix j, that is, if the two tokens encode to themselves side by side.
Prefixes are entered in the table as longest tokens reach them, with their last tokens; a trie over the vocabulary gives
the longest token at a position, and each token names the next shorter one that starts it. A prefix from which no token
leads on is marked dead and never entered again, and the one before it tries its next shorter token: every position of
a word is left at most once. When the end is entered, the last tokens are the ids. No merge queue is simulated.

Words are what the vocabulary's pre-tokenizer makes of a text: special tokens are taken out first, then NFC, lower
case, and a split at white space and between letters, digits and others. None of it reaches across white space, so
results are cached by white-space separated chunk and by word (bounded caches per worker). Chunks beyond ASCII are
normalised and split by the normalizer and pre-tokenizer that the vocabulary file describes, run by the tokenizers
library without any vocabulary, since Python's Unicode tables are of another version; chunks of ASCII and of composed
Latin letters up to U+017F, which no version splits otherwise, are split here. Ids always come from the programme here.

Defined cases: null text is the empty text with no ids (digests of the empty string); repeated rows are encoded one by
one; very long words cost time in proportion to their length; extra columns are ignored or kept, as stated.
"""

from __future__ import annotations

import hashlib
import json
import re
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from regioncount.llm.common import Recent, give_back, once_per_process, slices

#: Composed Latin letters beyond ASCII; the dotted capital I is left out, as its lower case is two characters.
_LATIN = "\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u017f"
#: Fixed value: the pre-tokenizer's pattern in the vocabulary file, for chunks of printable ASCII and those letters.
_PIECES = rf"'s|'t|'re|'ve|'m|'ll|'d|[a-zA-Z{_LATIN}]+|[0-9]|[^a-zA-Z0-9{_LATIN}]+"
_END = "\x01"
#: Chunks and token pairs that a task remembers; chunks where another stage's memory is still held beside it.
CACHE_ENTRIES, PAIR_ENTRIES, FEW_ENTRIES = 150_000, 300_000, 40_000


class Vocabulary:
    """A vocabulary file as it travels to workers: compressed, read by the driver alone, built once in a process."""

    def __init__(self, path: str):
        with open(path, "rb") as f:
            raw = f.read()
        self.key, self.packed = hashlib.sha256(raw).hexdigest(), zlib.compress(raw)

    def encoder(self) -> "Encoder":
        return once_per_process(self.key, lambda: Encoder(zlib.decompress(self.packed)))


class Encoder:
    """Vocabulary, merges and the automaton of a vocabulary file's content."""

    def __init__(self, raw: bytes):
        spec = json.loads(raw)
        self.vocab: dict[str, int] = spec["model"]["vocab"]
        self.merges = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        self.suffix: str = spec["model"]["end_of_word_suffix"]
        self.special: dict[str, int] = {t["content"]: t["id"] for t in spec["added_tokens"]}
        import ahocorasick
        import regex

        n = max(*self.vocab.values(), *self.special.values()) + 1
        self.token = [""] * n
        for text, i in [*self.vocab.items(), *self.special.items()]:
            self.token[i] = text
        # the merge that makes a token: its rank, left and right part; base symbols have rank -1
        self.rank, self.left, self.right, self.pair = [-1] * n, [-1] * n, [-1] * n, {}
        for r, (a, b) in enumerate(self.merges):
            i, j, k = self.vocab[a], self.vocab[b], self.vocab[a + b]
            self.pair[i * n + j] = r
            if self.rank[k] < 0:
                self.rank[k], self.left[k], self.right[k] = r, i, j
        self.n = n
        self.trie, written = ahocorasick.Automaton(), {}
        for text, i in self.vocab.items():
            if text not in self.special:
                written[text.removesuffix(self.suffix) + _END if text.endswith(self.suffix) and text != self.suffix else text] = i
        # for every beginning of a token, the longest token that starts it; for every token, the next shorter one
        self.length, self.shorter, self.best = [0] * n, [-1] * n, {"": -1}
        for text in sorted(written, key=len):
            i = written[text]
            self.trie.add_word(text, i)
            self.length[i] = len(text)
        self.longest = max(self.length)
        for text, i in written.items():
            for k in range(1, len(text) + 1):
                start = text[:k]
                if start not in self.best:
                    self.best[start] = next((written[start[:m]] for m in range(k, 0, -1) if start[:m] in written), -1)
        for text, i in written.items():
            self.shorter[i] = self.best[text[:-1]]
        self.split_words = self._splitter(spec)
        self.pieces, self.latin = re.compile(_PIECES).findall, re.compile(rf"[!-~{_LATIN}]+").fullmatch
        self.bytes = {ord(c): "".join(self.split_words(c)) for c in map(chr, range(0xC0, 0x180)) if self.latin(c) and c == c.lower()}
        self.chunks = regex.compile(r"\S+").findall
        self.specials = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")").split if self.special else None
        self.memories: list[Recent] = []
        self.cache = self.remember(self._entry, self._joined)
        self.words = Recent(self.word_ids, CACHE_ENTRIES)
        self.fits: dict[int, bool] = {}

    @staticmethod
    def _splitter(spec: dict):
        """Words of a chunk, in the byte alphabet, by the file's normalizer and pre-tokenizer alone."""
        import tokenizers

        empty = {"type": "BPE", "dropout": None, "unk_token": None, "continuing_subword_prefix": None, "end_of_word_suffix": None, "fuse_unk": False, "byte_fallback": False, "vocab": {}, "merges": []}
        steps = tokenizers.Tokenizer.from_str(json.dumps(spec | {"model": empty, "added_tokens": [], "truncation": None, "padding": None, "post_processor": None, "decoder": None}))
        normal, words = steps.normalizer.normalize_str, steps.pre_tokenizer.pre_tokenize_str
        return lambda chunk: [w for w, _ in words(normal(chunk))]

    def compatible(self, a: int, b: int) -> bool:
        """Whether a and b side by side stay as they are.

        Time runs backwards: the later of the merges inside a and b is undone, which shows the pieces that met at the
        border before it. Had they a merge of an earlier rank, it would have come first. At equal rank the left wins.
        """
        rank, pair, n = self.rank, self.pair, self.n
        before = len(self.merges)
        while True:
            r = pair.get(a * n + b)
            if r is not None and r < before:
                return False
            ra, rb = rank[a], rank[b]
            if ra < 0 and rb < 0:
                return True
            if ra > rb:
                before, a = ra, self.right[a]
            else:
                before, b = rb + 1, self.left[b]

    def word_ids(self, word: str) -> list[int]:
        """Ids of one word, given in the byte alphabet."""
        s, n, fits, length, shorter, best = word + _END, self.n, self.fits, self.length, self.shorter, self.best
        reach, longest, size = self.trie.longest_prefix, self.longest, len(word) + 1
        at, p, out, dead = 0, -1, [], set()
        while at < size:
            rest = s[at : at + longest]
            token = best[rest[: reach(rest)]]
            while True:
                while token >= 0:
                    if not dead or at + length[token] not in dead:
                        if p < 0:
                            break
                        key = p * n + token
                        ok = fits.get(key)
                        if ok is None:
                            if len(fits) >= PAIR_ENTRIES:
                                fits.clear()
                            ok = fits[key] = self.compatible(p, token)
                        if ok:
                            break
                    token = shorter[token]
                if token >= 0:
                    break
                if not out:
                    raise ValueError(f"the vocabulary does not cover {word!r}")
                dead.add(at)
                at -= length[p]
                token = shorter[out.pop()]
                p = out[-1] if out else -1
            out.append(token)
            at, p = at + length[token], token
        return out

    def chunk_ids(self, chunk: str) -> list[int]:
        """Ids of a chunk without white space."""
        if self.specials and "<|" in chunk:
            out = []
            for k, part in enumerate(self.specials(chunk)):
                if k % 2:
                    out.append(self.special[part])
                elif part:
                    out += self._plain(part)
            return out
        return self._plain(chunk)

    def _plain(self, chunk: str) -> list[int]:
        out: list[int] = []
        for word in self.chunk_words(chunk):
            out += self.words(word)
        return out

    def chunk_words(self, chunk: str) -> list[str]:
        """Words of a chunk without special tokens, in the byte alphabet."""
        if chunk.isascii() and chunk.isprintable():
            low = chunk.lower()
            return [low] if low.isalpha() else self.pieces(low)
        if self.latin(chunk):
            return [w if w.isascii() else w.translate(self.bytes) for w in self.pieces(chunk.lower())]
        return self.split_words(chunk)

    def remember(self, make, join, size: int = CACHE_ENTRIES, words: int | None = None) -> Recent:
        """Bounded memory, by chunk, of what `make` gives for ids; `join` puts the results of a chunk's words together."""
        known = Recent(lambda word: make(self.word_ids(word)), words or size)
        get, miss = known.get, known.miss

        def of(chunk: str):
            if self.specials and "<|" in chunk:
                return make(self.chunk_ids(chunk))
            found = [get(w) or miss(w) for w in self.chunk_words(chunk)]
            return found[0] if len(found) == 1 else join(found)

        kept = Recent(of, size)
        self.memories.append(known)
        self.memories.append(kept)
        return kept

    def forget(self) -> None:
        """Empty the caches and give their memory back: a worker lives on between tasks."""
        for kept in self.memories:
            kept.clear()
        del self.memories[2:]
        self.words.clear()
        self.fits.clear()
        give_back()

    def split(self, text: str) -> list[str]:
        """White-space separated chunks, white space as the vocabulary's pattern sees it."""
        if text.isascii() and not any(c in text for c in "\x1c\x1d\x1e\x1f"):
            return text.split()
        return self.chunks(text)

    def _entry(self, ids: list[int]) -> tuple[int, str, str]:
        """(number of ids, the ids, their tokens), each followed by a space."""
        if not ids:
            return 0, "", ""
        return len(ids), " ".join(map(str, ids)) + " ", " ".join([self.token[i] for i in ids]) + " "

    @staticmethod
    def _joined(found: list[tuple[int, str, str]]) -> tuple[int, str, str]:
        return sum([x[0] for x in found]), "".join([x[1] for x in found]), "".join([x[2] for x in found])

    def entries(self, text: str) -> list[tuple[int, str, str]]:
        get, miss = self.cache.get, self.cache.miss
        return [get(c) or miss(c) for c in self.split(text)]

    def encode(self, text: str | None) -> list[int]:
        return [i for c in self.split(text or "") for i in self.chunk_ids(c)]

    def decode(self, ids: list[int]) -> str:
        """The vocabulary file names no decoder: tokens are joined by a space."""
        return " ".join([self.token[i] for i in ids])


def load(path: str | None = None) -> Encoder:
    return Vocabulary(path or encoder_path()).encoder()


def encoder_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of every whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(Vocabulary(path or encoder_path()))
    docs = docs.select("doc_id", "text")
    id_type = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = shared.value.encoder()
        for batch in slices(batches):
            n, ids, decoded = [], [], []
            for text in batch.column(1):
                found = enc.entries(text.as_py() or "")
                n.append(sum([x[0] for x in found]))
                ids.append(hashlib.sha256("".join([x[1] for x in found])[:-1].encode()).hexdigest())
                decoded.append(hashlib.sha256("".join([x[2] for x in found])[:-1].encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(ids, pa.string()), pa.array(decoded, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])
        enc.forget()

    return docs.mapInArrow(run, f"doc_id {id_type}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def encode(docs: DataFrame, path: str | None = None, keep: list[str] | None = None) -> DataFrame:
    """The columns `keep` (doc_id by default), n_tokens and the ids of every whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(Vocabulary(path or encoder_path()))
    keep = keep or ["doc_id"]
    rows = docs.select(*keep, docs["text"].alias("__rc_text"))
    schema = ", ".join(f"`{c}` {rows.schema[c].dataType.simpleString()}" for c in keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        give_back()  # what stages before this one left in the worker
        enc = shared.value.encoder()
        found = enc.remember(lambda ids: array("i", ids).tobytes(), b"".join, FEW_ENTRIES)
        get, miss = found.get, found.miss
        for batch in slices(batches):
            lists = [b"".join([get(c) or miss(c) for c in enc.split(text.as_py() or "")]) for text in batch.column(len(keep))]
            sizes = [len(x) // 4 for x in lists]
            ids = pa.ListArray.from_arrays(pa.array(np.cumsum([0, *sizes]).astype(np.int32)), pa.array(np.frombuffer(b"".join(lists), np.int32)))
            n = pa.array(sizes, pa.int64())
            yield pa.RecordBatch.from_arrays([*[batch.column(k) for k in range(len(keep))], n, ids], names=[*keep, "n_tokens", "ids"])
        enc.forget()

    return rows.mapInArrow(run, f"{schema}, n_tokens long, ids array<int>")


def decode(encoded: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, decoded) from the ids."""
    shared = encoded.sparkSession.sparkContext.broadcast(Vocabulary(path or encoder_path()))
    rows = encoded.select("doc_id", "ids")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = shared.value.encoder()
        for batch in slices(batches):
            texts = [enc.decode(x.as_py() or []) for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "decoded"])

    return rows.mapInArrow(run, f"doc_id {rows.schema['doc_id'].dataType.simpleString()}, decoded string")
