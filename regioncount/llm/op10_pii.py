"""Personal data: base patterns, and a semi-Markov conditional random field that adds spans.

The field scores candidate segments of up to MAX_TOKENS tokens by features of the whole span (digit count and
grouping, separators, check digit, address shape, the word before it) for the types email, ip, card and phone. A
dynamic programme over token positions picks boundaries and types together: the best sum of segment scores, where a
token outside any segment scores 0. It is trained here by maximum likelihood (forward and backward sums over all
segmentations, in numpy) on generated sentences with known spans, so that no personal data is needed.

Only stretches around a digit, an at sign or the word `at` are decoded: no segment without one has features, and a
stretch holds every segment with its trigger and the tokens before that its features look at, so the best segmentation
of the whole text is the same.

Defined cases: null text is the empty text; offsets count code points, ends exclusive; repeated rows are searched one
by one; very long texts take linear time (no pattern backtracks over a run twice); extra columns are ignored by
`find` and kept by `redact`; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import random
import re
from collections.abc import Iterator
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from regioncount.llm.common import slices

KINDS = ("email", "ip", "card", "phone")
MAX_TOKENS = 16
REACH = 4

# ---------------------------------------------------------------- base patterns (fixed values of the contract)
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (1 + k % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def emails(text: str) -> Iterator[tuple[int, int]]:
    """Runs of local characters before an at sign, with a domain after it; each run is walked once."""
    floor, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > floor and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
            floor = m.end()
        at = text.find("@", max(at + 1, floor))


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end), by kind as listed, then by start."""
    out = [("email", *x) for x in emails(text)]
    if not _DIGIT.search(text):
        return out
    for m in _IP.finditer(text):
        if all(len(p) <= 3 and int(p) <= 255 if len(p) < 4 else int(p) <= 255 for p in _parts(m[0])):
            out.append(("ip", *m.span()))
    for m in _CARD.finditer(text):
        digits = m[0].replace(" ", "").replace("-", "")
        if 16 <= len(digits) <= 19 and luhn(digits):
            out.append(("card", *m.span()))
    if "+" in text:
        for m in _PHONE.finditer(text):
            if 8 <= sum(c.isdigit() for c in m[0]) <= 15:
                out.append(("phone", *m.span()))
    return out


def _parts(address: str) -> list[str]:
    """Parts without leading zeros, at most four digits of each kept: enough to compare with 255."""
    return [(p.lstrip("0") or "0")[:4] for p in address.split(".")]


# ---------------------------------------------------------------- tokens and span features
_TOKEN = re.compile(r"[^\W\d_]+|[0-9]+|[^\s]")
#: A digit, an at sign or the token `at`; every segment with features has one.
_TRIGGER = re.compile(r"[\d@]|at(?<![^\W\d_]at)(?![^\W\d_])")
#: The rest of a word, and the words that a segment with it can reach: not past a line's end. Before it (read from
#: right to left), also the two tokens that features look at.
_AHEAD = re.compile(rf"(\S*+)(?:[^\S\n]++\S++){{0,{MAX_TOKENS - 1}}}+")
_BACK = re.compile(rf"\S*+(?:[^\S\n]++\S++){{0,{MAX_TOKENS - 1}}}+(?:\s++\S++){{0,2}}+")
#: Words that announce a kind of personal data (fixed list).
_CUES = {"email": 0, "mail": 0, "contact": 0, "ip": 1, "host": 1, "address": 1, "card": 2, "visa": 2, "payment": 2, "phone": 3, "tel": 3, "call": 3, "mobile": 3, "fax": 3}
#: What continues an address or a number after its end.
_GOES_ON = re.compile(r"[.@/-][A-Za-z0-9]|\s[\[(]?(?:dot|at)[\])]?\s")


def tokens(text: str, start: int = 0, end: int | None = None) -> list[tuple[str, int, int]]:
    return [(m[0], *m.span()) for m in _TOKEN.finditer(text, start, len(text) if end is None else end)]


FEATURES = ("bias", "tokens", "digits<7", "digits7", "digits8-9", "digits10", "digits11", "digits12-15", "digits16-19", "digits>19", "luhn", "plus", "parens", "dash", "space", "dot", "slash", "colon", "other", "letters", "at", "spelled_at", "domain", "local", "four_parts", "octets", "groups_phone", "groups_card", "one_run", "date", "starts_1", "cue_email", "cue_ip", "cue_card", "cue_phone", "equals_before", "currency_before", "unbalanced", "goes_on", "began_before")
INDEX = {name: k for k, name in enumerate(FEATURES)}


def span_features(toks: list[tuple[str, int, int]], i: int, j: int, text: str) -> list[int] | None:
    """Features of the segment of tokens i..j-1; None if it can be no entity."""
    s, e = toks[i][1], toks[j - 1][2]
    if s and (text[s - 1].isalnum() or text[s - 1] == "_") or e < len(text) and (text[e].isalnum() or text[e] == "_"):
        return None
    span = text[s:e]
    if "\n" in span:
        return None
    words = [t[0] for t in toks[i:j]]
    n = sum(map(len, filter(str.isdecimal, words)))
    has_at = "@" in span
    spelled = not has_at and any(w in ("at",) for w in words[1:-1]) and ("dot" in words or "." in words)
    if not (n >= 4 or has_at or spelled):
        return None
    first, last = words[0], words[-1]
    if not (first.isalnum() or first in "+(") or not last.isalnum():
        return None
    f = ["bias"]
    if not (has_at or spelled):
        f.append("digits<7" if n < 7 else "digits7" if n == 7 else "digits8-9" if n < 10 else "digits10" if n == 10 else "digits11" if n == 11 else "digits12-15" if n < 16 else "digits16-19" if n < 20 else "digits>19")
        groups = [len(w) for w in words if w.isdecimal()]
        if n >= 16 and n < 20 and luhn("".join(w for w in words if w.isdecimal())):
            f.append("luhn")
        if groups[-3:] == [3, 3, 4] or groups[-2:] == [3, 4] and len(groups) > 1:
            f.append("groups_phone")
        if groups == [4, 4, 4, 4] or groups == [4, 6, 5]:
            f.append("groups_card")
        if len(groups) == 1:
            f.append("one_run")
        if len(groups) == 3 and sorted(groups) in ([2, 2, 4], [1, 2, 4], [1, 1, 4]) or len(groups) in (2, 3) and max(groups) <= 2:
            f.append("date")
        if len(groups) == 4 and span.count(".") == 3:
            f.append("four_parts")
            if all(int(w[:4]) <= 255 for w in words if w.isdecimal()) and len(words) == 7:
                f.append("octets")
        if words[0] == "+":
            f.append("plus")
        if "(" in span:
            f.append("parens" if span.count("(") == span.count(")") == 1 else "unbalanced")
        elif ")" in span:
            f.append("unbalanced")
        for c, name in (("-", "dash"), (" ", "space"), (".", "dot"), ("/", "slash"), (":", "colon")):
            if c in span:
                f.append(name)
        if any(w.isalpha() for w in words):
            f.append("letters")
        if any(len(w) == 1 and not w.isalnum() and w not in "+-(). /:" for w in words):
            f.append("other")
        if words[0] == "1":
            f.append("starts_1")
    else:
        f.append("at" if has_at else "spelled_at")
        local, _, domain = span.partition("@") if has_at else re.sub(r"\s*[\[(]?\bdot\b[\])]?\s*", ".", span).replace("[at]", " at ").replace("(at)", " at ").partition(" at ")
        if re.fullmatch(r"\s*[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,8}\s*", domain):
            f.append("domain")
        if re.fullmatch(r"[A-Za-z0-9._%+-]{2,64}\s*", local):
            f.append("local")
        if span.count("@") > 1:
            f.append("other")
        if " " in span and has_at:
            f.append("space")
    if _GOES_ON.match(text, e):
        f.append("goes_on")
    if s > 1 and text[s - 1] in ".-+@/" and text[s - 2].isalnum() or s and text[s - 1] in "+@":
        f.append("began_before")
    if i:
        before = toks[i - 1][0].lower()
        near = before if before.isalpha() or i < 2 else toks[i - 2][0].lower()
        if near in _CUES:
            f.append(f"cue_{KINDS[_CUES[near]]}")
        if before in ("=", '"', "#"):
            f.append("equals_before")
        if before in ("$", "€", "£"):
            f.append("currency_before")
    return [INDEX[x] for x in f]


def segments(toks: list[tuple[str, int, int]], text: str) -> list[tuple[int, int, list[int]]]:
    out = []
    digits, ats, words, dots = ([0, *accumulate(of(t[0]) for t in toks)] for of in (lambda w: len(w) * w.isdecimal(), "@".__eq__, "at".__eq__, (".", "dot").__contains__))
    for i in range(len(toks)):
        for j in range(i + 1, min(i + MAX_TOKENS, len(toks)) + 1):
            # without one of these, span_features is None
            if digits[j] - digits[i] >= 4 or ats[j] > ats[i] or j > i + 2 and words[j - 1] > words[i + 1] and dots[j] > dots[i]:
                f = span_features(toks, i, j, text)
                if f:
                    out.append((i, j, f))
    return out


# ---------------------------------------------------------------- training
def sentences(n: int, seed: int = 7) -> list[tuple[str, list[tuple[str, int, int]]]]:
    """Generated sentences with known spans, and with numbers that are no personal data."""
    rng = random.Random(seed)
    digits = lambda k: "".join(rng.choice("0123456789") for _ in range(k))
    word = lambda a=2, b=9: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(a, b)))
    host = lambda: f"{word(3)}{rng.choice(['', digits(1)])}.{rng.choice(['', word(3) + '.'])}{rng.choice(['com', 'org', 'net', 'de', 'fr', 'io', 'info'])}"

    def card() -> str:
        d = rng.choice("3456") + digits(14)
        d += next(c for c in "0123456789" if luhn(d + c))
        return rng.choice([d, d, f"{d[:4]} {d[4:8]} {d[8:12]} {d[12:]}", f"{d[:4]}-{d[4:8]}-{d[8:12]}-{d[12:]}"])

    def phone() -> str:
        a, b, c = digits(3), digits(3), digits(4)
        return rng.choice([f"+1 ({a}) {b}-{c}", f"+1 ({a}) {b}-{c}", f"+{digits(2)} {a} {b} {c}", f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"1-{a}-{b}-{c}", f"+{digits(2)}{a}{b}{c}", f"{a}.{b}.{c}"])

    def email() -> str:
        name = f"{word(3)}{rng.choice(['', '.' + digits(2), '_' + word(2), digits(2)])}"
        h = host()
        return rng.choice([f"{name}@{h}", f"{name}@{h}", f"{word(3)} at {h.replace('.', ' dot ')}", f"{word(3)} [at] {h.replace('.', ' [dot] ')}", f"{word(3)} (at) {h}"])

    def unlucky() -> str:
        d = digits(15)
        return d + rng.choice([c for c in "0123456789" if not luhn(d + c)])

    made = {"email": email, "ip": lambda: ".".join(str(rng.randint(0, 255)) for _ in range(4)), "card": card, "phone": phone}
    nothing = [
        lambda: str(rng.randint(1, 99999)), lambda: f"{rng.randint(1900, 2030)}-{rng.randint(1, 12):02}-{rng.randint(1, 28):02}", lambda: f"{rng.randint(1, 28)}/{rng.randint(1, 12)}/{rng.randint(1990, 2030)}",
        lambda: f"{rng.randint(0, 23)}:{digits(2)}", lambda: f"v{rng.randint(0, 9)}.{rng.randint(0, 30)}.{rng.randint(0, 9)}", lambda: f"${digits(2)}.{digits(2)}", lambda: digits(rng.choice([5, 6, 8, 9, 12, 13, 14, 20, 24])), lambda: unlucky(),
        lambda: 'token = "' + "".join(rng.choice("0123456789abcdef") for _ in range(40)) + '"', lambda: "password=" + "".join(rng.choice("0123456789abcdef") for _ in range(18)), lambda: "AKIA" + "".join(rng.choice("ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789") for _ in range(16)),
        lambda: f"{digits(3)}-{digits(3)}", lambda: f"{rng.randint(256, 999)}.{digits(3)}.{digits(3)}.{digits(3)}", lambda: f"@{word()}", lambda: f"{word()} at {word()}", lambda: f"{rng.randint(1, 9)},{digits(3)},{digits(3)}", lambda: f"{digits(4)} {digits(4)}", lambda: f"({rng.randint(1, 2030)})", lambda: f"{digits(4)} {digits(3)}",
    ]
    out = []
    for _ in range(n):
        text, spans = "", []
        for _ in range(rng.randint(1, 4)):
            text += " ".join(word() for _ in range(rng.randint(0, 3))) + rng.choice([" ", " ", ", "]) if rng.random() < 0.8 else ""
            if rng.random() < 0.55:
                kind = rng.choice(KINDS)
                if rng.random() < 0.25:
                    text += rng.choice([c for c, k in _CUES.items() if KINDS[k] == kind]) + rng.choice([" ", ": "])
                s = made[kind]()
                spans.append((kind, len(text), len(text) + len(s)))
            else:
                s = rng.choice(nothing)()
            text += s + rng.choice([" ", ". ", ", ", "\n"])
        out.append((text, spans))
    return out


def train(n_sentences: int = 900, epochs: int = 120, l2: float = 0.02, seed: int = 7) -> np.ndarray:
    """Weights (feature, kind) by maximum likelihood over segmentations; n_sentences bounds the training set."""
    feats, at, gold, lengths = [], [], [], []
    for k, (text, spans) in enumerate(sentences(n_sentences, seed)):
        toks, want = tokens(text), {(s, e): KINDS.index(kind) for kind, s, e in spans}
        lengths.append(len(toks))
        for i, j, f in segments(toks, text):
            feats.append(f)
            at.append((k, i, j))
            gold.append(want.get((toks[i][1], toks[j - 1][2]), -1))
    x = np.zeros((len(feats), len(FEATURES)))
    for r, f in enumerate(feats):
        x[r, f] = 1
    at, gold = np.array(at), np.array(gold)
    n, top = len(lengths), max(lengths)
    ends = [np.flatnonzero(at[:, 2] == j) for j in range(top + 1)]
    begins = [np.flatnonzero(at[:, 1] == i) for i in range(top + 1)]
    right = gold >= 0
    target = np.zeros((len(FEATURES), len(KINDS)))
    np.add.at(target.T, gold[right], x[right])
    w, m, v = np.zeros_like(target), np.zeros_like(target), np.zeros_like(target)
    for step in range(1, epochs + 1):
        score = x @ w
        whole = np.logaddexp.reduce(score, axis=1)
        alpha, beta = np.zeros((n, top + 1)), np.zeros((n, top + 2))
        for j in range(1, top + 1):
            acc = np.exp(np.zeros(n))
            base = alpha[:, j - 1]
            if len(ends[j]):
                e = ends[j]
                np.add.at(acc, at[e, 0], np.exp(np.clip(alpha[at[e, 0], at[e, 1]] + whole[e] - base[at[e, 0]], -50, 50)))
            alpha[:, j] = base + np.log(acc)
        for i in range(top - 1, -1, -1):
            acc, base = np.ones(n), beta[:, i + 1]
            if len(begins[i]):
                b = begins[i]
                np.add.at(acc, at[b, 0], np.exp(np.clip(beta[at[b, 0], at[b, 2]] + whole[b] - base[at[b, 0]], -50, 50)))
            beta[:, i] = base + np.log(acc)
        p = np.exp(np.clip(alpha[at[:, 0], at[:, 1]][:, None] + score + beta[at[:, 0], at[:, 2]][:, None] - alpha[at[:, 0], -1][:, None], -50, 0))
        grad = (target - x.T @ p) / n - l2 * w / n
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        w = w + 0.15 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return w


# ---------------------------------------------------------------- decoding
def decode(text: str, weights: np.ndarray, start: int = 0, end: int | None = None) -> list[tuple[str, int, int]]:
    """Best segmentation of text[start:end]."""
    toks = tokens(text, start, end)
    by_end: dict[int, list[tuple[float, int, int]]] = {}
    for i, j, f in segments(toks, text):
        scores = weights[f].sum(axis=0)
        k = int(scores.argmax())
        if scores[k] > 0:
            by_end.setdefault(j, []).append((float(scores[k]), i, k))
    if not by_end:
        return []
    best, back = [0.0] * (len(toks) + 1), [None] * (len(toks) + 1)
    for j in range(1, len(toks) + 1):
        best[j], back[j] = best[j - 1], None
        for s, i, k in by_end.get(j, ()):
            if best[i] + s > best[j]:
                best[j], back[j] = best[i] + s, (i, k)
    out, j = [], len(toks)
    while j:
        if back[j] is None:
            j -= 1
        else:
            i, k = back[j]
            out.append((KINDS[k], toks[i][1], toks[j - 1][2]))
            j = i
    return out[::-1]


def stretches(text: str) -> Iterator[tuple[int, int]]:
    """Disjoint stretches around triggers, cut at white space, that hold all segments with features."""
    begin = end = word = -1
    back = ""
    for m in _TRIGGER.finditer(text):
        if m.start() < word:
            continue
        back = back or text[::-1]
        ahead = _AHEAD.match(text, m.end())
        floor = max(end - 1, 0)  # with the last word before it, the stretches are one
        a = len(text) - _BACK.match(back, len(text) - m.start(), len(text) - floor).end() if m.start() > floor else floor
        if begin < 0 or a > end:
            if m[0] == "at" and "." not in (near := text[a : ahead.end()]) and "dot" not in near:
                continue
            if begin >= 0:
                yield begin, end
            begin = a
        end, word = max(end, ahead.end()), ahead.end(1)
    if begin >= 0:
        yield begin, end


def all_spans(text: str, weights: np.ndarray) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
    """(base spans, all spans): the field adds spans that overlap no base span."""
    base = base_spans(text)
    taken = sorted((s, e) for _, s, e in base)
    added, upto = [], 0
    for a, b in stretches(text):
        a = max(a, upto)
        upto = b
        for kind, s, e in decode(text, weights, a, b):
            if not any(s < y and x < e for x, y in taken):
                added.append((kind, s, e))
    return base, sorted([*base, *added], key=lambda x: (KINDS.index(x[0]), x[1]))


def written(spans: list[tuple[str, int, int]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for k, s, e in spans)


def find(docs: DataFrame, weights: np.ndarray | None = None) -> DataFrame:
    """The contract's columns for every whole text; n_added counts the spans that the field adds."""
    weights = train() if weights is None else weights
    docs = docs.select("doc_id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            counts, sha, spans, more = [[] for _ in KINDS], [], [], []
            for x in batch.column(1):
                base, every = all_spans(x.as_py() or "", weights)
                for k, kind in enumerate(KINDS):
                    counts[k].append(sum(b[0] == kind for b in base))
                sha.append(hashlib.sha256(written(base).encode()).hexdigest())
                spans.append(written(every))
                more.append(len(every) - len(base))
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(c, pa.int64()) for c in counts], pa.array(sha, pa.string()), pa.array(spans, pa.string()), pa.array(more, pa.int64())], names=["doc_id", *[f"n_{k}" for k in KINDS], "base_sha256", "spans", "n_added"])

    id_type = docs.schema["doc_id"].dataType.simpleString()
    return docs.mapInArrow(run, f"doc_id {id_type}, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long")


def mask(text: str, spans: list[tuple[str, int, int]]) -> str:
    """Spans replaced by their kind in brackets; overlapping ones are replaced together, under the first one's kind."""
    out, at = [], 0
    for kind, s, e in sorted(spans, key=lambda x: (x[1], -x[2])):
        if s >= at:
            out += [text[at:s], f"[{kind.upper()}]"]
        at = max(at, e)
    return "".join([*out, text[at:]])


def redact(docs: DataFrame, weights: np.ndarray | None = None) -> DataFrame:
    """All rows and columns, with every span in the column `text` replaced; null texts stay null."""
    weights = train() if weights is None else weights
    names, at = docs.columns, [c.lower() for c in docs.columns].index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            texts = [None if x is None else mask(x, all_spans(x, weights)[1]) for x in batch.column(at).to_pylist()]
            columns = batch.columns
            columns[at] = pa.array(texts, batch.column(at).type)
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return docs.mapInArrow(run, docs.schema)


def redact_documents(docs: DataFrame, weights: np.ndarray | None = None) -> DataFrame:
    """`redact`, and n_chars (where there is one) set to the new length in code points."""
    out = redact(docs, weights)
    names = {c.lower(): c for c in out.columns}
    if "n_chars" not in names:
        return out
    n = names["n_chars"]
    return out.withColumn(n, F.char_length("text").cast(out.schema[n].dataType))
