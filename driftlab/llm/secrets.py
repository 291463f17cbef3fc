"""Secret scans: base patterns, and formats learned by grammar inference.

The base patterns find three kinds of credential. Their matches are labelled examples: up to
`max_examples` distinct ones of each kind, and `max_background` other tokens, those of smallest hash over the whole table, are brought to the
driver. A fifth of each is held out. Of the others, each kind and the background build a prefix tree (of strings of
character classes) whose states are merged wherever their outgoing frequencies are statistically
compatible (Hoeffding bound, applied down both subtrees), which leaves a small deterministic
probabilistic automaton. Its transitions are smoothed; a class that no example showed in a state costs its small probability and keeps the
state. The examples' lengths are part of the format. Every maximal token of credential characters in every text is a candidate, of the least length of the base kinds on, and is
scored: the log likelihood under the best kind's automaton less that under the background's, per character. The threshold is the ratio that nine in
ten of the held-out credentials reach, so a candidate must be as typical of a known format as they are; and its whole ratio must be `margin` or more: odds of e^margin. Tokens above it
that no base match overlaps are added as kind `format`. What the held-out examples say of the threshold comes with it (`Formats`).

Defined cases: null text is empty; a kind with fewer than `min_examples` examples has no automaton and adds nothing, and so does a table
without background tokens; an empty table gives an empty result; rows that repeat are scanned each.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterable, Iterator, Sequence
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_hash, chunks, ship, text_buffer, token_names

# The base patterns.
ASSIGN = re.compile(rb"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE)
ACCESS = re.compile(rb"AKIA[A-Z0-9]+")
ASSIGN_LEAST, ACCESS_LEAST, HEX_LEAST = 6, 20, 24
KEYWORDS = (b"password", b"passwd", b"secret", b"token", b"api")
KINDS = ("assign", "access", "hex", "format")

#: Tokens shorter than the shortest base credential are not candidates.
TOKEN_LEAST = ASSIGN_LEAST

_HEX = np.zeros(256, bool)
_HEX[list(b"0123456789abcdef")] = True
_TOKEN = np.zeros(256, bool)
_TOKEN[list(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_.=-")] = True
#: Character classes: digit, a-f, g-z, A-F, G-Z, and each sign by itself; then the end of the token.
_CLASS = np.zeros(256, np.int8)
for _k, _chars in enumerate((b"0123456789", b"abcdef", b"ghijklmnopqrstuvwxyz", b"ABCDEF", b"GHIJKLMNOPQRSTUVWXYZ", b"+", b"/", b"_", b".", b"=", b"-")):
    _CLASS[list(_chars)] = _k
N_CLASSES = 11
END = N_CLASSES


class Automaton:
    """Deterministic probabilistic automaton: next[state, class], logp[state, class or END].

    sizes: log probability of each length, which then stands in for the ends and makes the other transitions conditional on going on.
    """

    def __init__(self, follow: np.ndarray, logp: np.ndarray, sizes: np.ndarray | None = None):
        self.follow, self.logp, self.sizes = follow, logp, sizes
        self.going = np.log1p(-np.exp(logp[:, END]))

    def likelihood(self, tokens: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Log likelihood of each span by the automaton's transitions and the lengths of its examples."""
        return self.scores(tokens, starts, ends, True) + self.sizes[np.minimum(ends - starts, len(self.sizes) - 1)]

    def scores(self, tokens: np.ndarray, starts: np.ndarray, ends: np.ndarray, inner: bool = False) -> np.ndarray:
        """Log likelihood of each span of a class array, all spans in step. inner: of its characters, given its length."""
        order = np.argsort(starts - ends, kind="stable")  # longest first
        lengths = (ends - starts)[order]
        base = starts[order]
        state = np.zeros(len(order), np.int64)
        total = np.zeros(len(order))
        for k in range(int(lengths.max(initial=0))):
            live = int(np.searchsorted(-lengths, -k, side="left"))
            c = tokens[base[:live] + k]
            total[:live] += self.logp[state[:live], c] - (self.going[state[:live]] if inner else 0.0)
            state[:live] = self.follow[state[:live], c]
        if not inner:
            total += self.logp[state, END]
        out = np.empty(len(order))
        out[order] = total
        return out


def learn(examples: Iterable[bytes], alpha: float = 0.05, smoothing: float = 0.5) -> Automaton:
    """Merges the states of the examples' prefix tree that are statistically compatible. smoothing: examples' worth given to every transition, above 0."""
    examples = list(examples)
    children: list[dict[int, int]] = [{}]
    passed: list[int] = [0]
    ended: list[int] = [0]
    taken: list[dict[int, int]] = [{}]
    for text in examples:
        at = 0
        passed[0] += 1
        for c in _CLASS[np.frombuffer(text, np.uint8)].tolist():
            taken[at][c] = taken[at].get(c, 0) + 1
            nxt = children[at].get(c)
            if nxt is None:
                nxt = children[at][c] = len(children)
                children.append({})
                passed.append(0)
                ended.append(0)
                taken.append({})
            at = nxt
            passed[at] += 1
        ended[at] += 1
    width = math.sqrt(0.5 * math.log(2 / alpha))

    def differ(f: int, n: int, g: int, m: int) -> bool:
        return abs(f / n - g / m) > width * (1 / math.sqrt(n) + 1 / math.sqrt(m))

    def compatible(a: int, b: int) -> bool:
        stack = [(a, b)]
        while stack:
            x, y = stack.pop()
            n, m = passed[x], passed[y]
            if differ(ended[x], n, ended[y], m):
                return False
            for c in sorted({*taken[x], *taken[y]}):
                if differ(taken[x].get(c, 0), n, taken[y].get(c, 0), m):
                    return False
                if c in children[x] and c in children[y]:
                    stack.append((children[x][c], children[y][c]))
        return True

    def fold(a: int, b: int) -> None:
        stack = [(a, b)]
        while stack:
            x, y = stack.pop()
            passed[x] += passed[y]
            ended[x] += ended[y]
            for c, n in taken[y].items():
                taken[x][c] = taken[x].get(c, 0) + n
            for c, z in children[y].items():
                if c in children[x]:
                    stack.append((children[x][c], z))
                else:
                    children[x][c] = z

    settled = [0]
    while True:
        open_ = [(s, c, children[s][c]) for s in settled for c in sorted(children[s]) if children[s][c] not in settled]
        if not open_:
            break
        # the most visited open state is compared with every settled one
        s, c, new = max(open_, key=lambda e: (passed[e[2]], -e[2]))
        for old in settled:
            if compatible(old, new):
                children[s][c] = old
                fold(old, new)
                break
        else:
            settled.append(new)
    number = {s: k for k, s in enumerate(settled)}
    # a class that was never seen in a state keeps the state
    follow = np.repeat(np.arange(len(settled))[:, None], N_CLASSES + 1, axis=1)
    weight = np.full((len(settled), N_CLASSES + 1), smoothing)
    for s, k in number.items():
        weight[k, END] += ended[s]
        for c, n in taken[s].items():
            weight[k, c] += n
            follow[k, c] = number[children[s][c]]
    total = weight.sum(axis=1, keepdims=True)
    return Automaton(follow, np.log(weight / total), _lengths([len(t) for t in examples]))


#: Lengths from here on are one.
_LONG = 512


def _lengths(sizes: Sequence[int]) -> np.ndarray:
    """Log probability of each length: the examples' own, with one more example spread geometrically around their mean."""
    n, mean = len(sizes), max(1.0, sum(sizes) / max(1, len(sizes)))
    spread = (1 / mean) * (1 - 1 / mean) ** np.arange(_LONG + 1) if mean > 1 else 0.5 ** np.arange(1, _LONG + 2)
    count = np.bincount(np.minimum(sizes, _LONG), minlength=_LONG + 1) if n else np.zeros(_LONG + 1)
    return np.log(np.maximum((count + spread) / (n + 1), 1e-300))


def _runs(mask: np.ndarray, offsets: np.ndarray, least: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, end, document of the maximal runs of a mask inside one document."""
    if not len(mask):
        return (np.zeros(0, np.int64),) * 3
    first, last = mask.copy(), mask.copy()
    first[1:] &= ~mask[:-1]
    last[:-1] &= ~mask[1:]
    full = offsets[:-1] < offsets[1:]
    first[offsets[:-1][full]] = mask[offsets[:-1][full]]
    last[offsets[1:][full] - 1] = mask[offsets[1:][full] - 1]
    start, end = np.flatnonzero(first), np.flatnonzero(last) + 1
    long = end - start >= least
    start, end = start[long], end[long]
    return start, end, np.searchsorted(offsets, start, side="right") - 1


def _holders(raw: bytes, needle: bytes, offsets: np.ndarray) -> set[int]:
    """Documents of a chunk in whose bytes the needle starts."""
    at, found = raw.find(needle), []
    while at >= 0:
        found.append(at)
        at = raw.find(needle, at + 1)
    return set((np.searchsorted(offsets, np.array(found, np.int64), side="right") - 1).tolist()) if found else set()


def base_spans(flat: np.ndarray, offsets: np.ndarray) -> list[tuple[int, int, int, int, int]]:
    """(document, start, end, kind number, start of the credential) in bytes of the document."""
    raw = flat.tobytes()
    out = []
    start, end, doc = _runs(_HEX[flat], offsets, HEX_LEAST)
    for s, e, d in zip(start.tolist(), end.tolist(), doc.tolist(), strict=True):
        a = int(offsets[d])
        out.append((d, s - a, e - a, 2, s - a))
    for d in _holders(raw, b"AKIA", offsets):
        for m in ACCESS.finditer(raw, int(offsets[d]), int(offsets[d + 1])):
            if m.end() - m.start() >= ACCESS_LEAST:
                a = int(offsets[d])
                out.append((d, m.start() - a, m.end() - a, 1, m.start() - a))
    small = raw.lower()
    for d in set().union(*(_holders(small, k, offsets) for k in KEYWORDS)):
        for m in ASSIGN.finditer(raw, int(offsets[d]), int(offsets[d + 1])):
            if m.end(2) - m.start(2) >= ASSIGN_LEAST:
                a = int(offsets[d])
                out.append((d, m.start() - a, m.end() - a, 0, m.start(2) - a))
    return out


def _overlaps(spans: list[tuple[int, int]], s: int, e: int) -> bool:
    return any(a < e and s < b for a, b in spans)


def _fewest(held: dict[int, dict[bytes, int]], most: Sequence[int], slack: int = 1) -> None:
    """Keeps, of each kind, the most[kind] tokens of smallest hash, once there are `slack` times as many."""
    for kind, tokens in held.items():
        if len(tokens) > slack * most[kind]:
            held[kind] = dict(sorted(tokens.items(), key=lambda t: (t[1], t[0]))[: most[kind]])


def _token_batch(held: dict[int, dict[bytes, int]]) -> pa.RecordBatch:
    rows = [(k, t) for k, tokens in sorted(held.items()) for t in tokens]
    return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary())], names=["kind", "token"])


def _examples(most: Sequence[int]):
    """(kind, token): credentials of base matches, and other tokens as kind 3; the most[kind] of smallest hash in a partition."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, dict[bytes, int]] = {}
        for b in batches:
            flat, off = text_buffer(b.column(0))
            for i, j in chunks(off):
                a = off[i]
                part, inner = flat[a : off[j]], off[i : j + 1] - a
                raw = part.tobytes()
                by: dict[int, list] = {}
                for d, s, e, k, c in base_spans(part, inner):
                    at = int(inner[d])
                    by.setdefault(d, []).append((at + s, at + e))
                    token = raw[at + c : at + e]
                    held.setdefault(k, {})[token] = xxhash.xxh64_intdigest(token, 5)
                start, end, doc = _runs(_TOKEN[part], inner, TOKEN_LEAST)
                other = held.setdefault(3, {})
                # of tokens that repeat in the chunk, one is looked at
                fresh = np.unique(byte_hash(part, 2).of(start, end), return_index=True)[1]
                for s, e, d in zip(start[fresh].tolist(), end[fresh].tolist(), doc[fresh].tolist(), strict=True):
                    if d not in by or not _overlaps(by[d], s, e):
                        token = raw[s:e]
                        other[token] = xxhash.xxh64_intdigest(token, 5)
                _fewest(held, most, 2)
        _fewest(held, most)
        yield _token_batch(held)

    return run


def _fold_examples(most: Sequence[int]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, dict[bytes, int]] = {}
        for b in batches:
            for k, t in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                held.setdefault(k, {})[t] = xxhash.xxh64_intdigest(t, 5)
            _fewest(held, most, 2)
        _fewest(held, most)
        yield _token_batch(held)

    return run


class Formats(NamedTuple):
    """Automata of assign, access, hex and background, thresholds of the log likelihood ratio per character and in all, and their record on held-out examples.

    held_out: examples of each of the four; caught: those that pass.
    """

    automata: list[Automaton | None]
    threshold: float
    margin: float
    held_out: list[int]
    caught: list[int]

    def ratio(self, classes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        like = np.max([x.likelihood(classes, starts, ends) for x in self.automata[:3] if x is not None], axis=0)
        return like - self.automata[3].likelihood(classes, starts, ends)

    def passes(self, classes: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        ratio = self.ratio(classes, starts, ends)
        return (ratio >= self.margin) & (ratio >= self.threshold * (ends - starts))

    def ready(self) -> bool:
        return self.automata[3] is not None and any(x is not None for x in self.automata[:3])


def _spans(tokens: Sequence[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Classes of the tokens end to end, starts, ends."""
    sizes = np.array([len(t) for t in tokens], np.int64)
    return _CLASS[np.frombuffer(b"".join(tokens), np.uint8)], np.cumsum(sizes) - sizes, np.cumsum(sizes)


def calibrate(examples: Sequence[Sequence[bytes]], min_examples: int = 8, alpha: float = 0.05, margin: float = 7.0, recall: float = 0.9, smoothing: float = 0.05) -> Formats:
    """Formats from examples of assign, access, hex and background; every fifth of each, by hash, is held out for the threshold.

    recall: share of the held-out credentials that the threshold lets pass.
    """
    out = lambda t: xxhash.xxh64_intdigest(t, 9) % 5 == 0
    kept, held = ([[t for t in kind if out(t) is side] for kind in examples] for side in (False, True))
    automata = [learn(t, alpha, smoothing) if len(t) >= (min_examples if kind < 3 else 1) else None for kind, t in enumerate(kept)]
    formats = Formats(automata, 0.0, margin, [len(h) for h in held], [0] * 4)
    if not formats.ready():
        return formats
    classes, starts, ends = _spans([t for kind in range(3) if automata[kind] for t in held[kind] or kept[kind]])
    threshold = max(0.0, float(np.quantile(formats.ratio(classes, starts, ends) / (ends - starts), 1 - recall)))
    formats = formats._replace(threshold=threshold)
    return formats._replace(caught=[int(formats.passes(*_spans(h)).sum()) if h else 0 for h in held])


def infer_formats(docs: DataFrame, text_col: str = "text", max_examples: int = 500, min_examples: int = 8, alpha: float = 0.05, margin: float = 7.0, max_background: int = 4000) -> Formats:
    """Formats from at most max_examples distinct tokens of each kind and max_background others of the table.

    Partitions, then 16 folding tasks, each keep the tokens of smallest hash, so the driver gets at most 16 times so many tokens.
    """
    ship(docs.sparkSession)
    shape = "kind int, token binary"
    most = (max_examples, max_examples, max_examples, max_background)
    local = docs.select(F.col(text_col).cast("string").alias("text")).mapInArrow(_examples(most), shape)
    held: dict[int, dict[bytes, int]] = {}
    for r in local.repartition(16, F.xxhash64("token") % 16).mapInArrow(_fold_examples(most), shape).collect():
        token = bytes(r.token)
        held.setdefault(r.kind, {})[token] = xxhash.xxh64_intdigest(token, 5)
    _fewest(held, most)
    return calibrate([sorted(held.get(kind, {})) for kind in range(4)], min_examples, alpha, margin)


def _scan(formats: Formats):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat, off = text_buffer(b.column(1))
            n = len(off) - 1
            counts = np.zeros((3, n), np.int64)
            digests = [hashlib.sha256(b"").hexdigest()] * n
            lists = [""] * n
            for i, j in chunks(off):
                a = off[i]
                part, inner = flat[a : off[j]], off[i : j + 1] - a
                by: dict[int, list[tuple[int, int, int]]] = {}
                for d, s, e, k, _ in base_spans(part, inner):
                    by.setdefault(d, []).append((s, k, e))
                extra: dict[int, list[tuple[int, int, int]]] = {}
                start, end, doc = _runs(_TOKEN[part], inner, TOKEN_LEAST)
                if len(start) and formats.ready():
                    # tokens that repeat in the chunk are scored once
                    _, lead, back = np.unique(token_names(part, start, end), return_index=True, return_inverse=True)
                    high = formats.passes(_CLASS[part], start[lead], end[lead])
                    for at in np.flatnonzero(high[back]).tolist():
                        d = int(doc[at])
                        s, e = int(start[at] - inner[d]), int(end[at] - inner[d])
                        if not _overlaps([(x, z) for x, _, z in by.get(d, [])], s, e):
                            extra.setdefault(d, []).append((s, 3, e))
                for d in {*by, *extra}:
                    text = part[inner[d] : inner[d + 1]]
                    lead = np.cumsum((text & 0xC0) != 0x80)  # code points up to each byte

                    def points(spans: list[tuple[int, int, int]], lead=lead) -> str:
                        at = lambda x: int(lead[x - 1]) if x else 0
                        return ",".join(f"{KINDS[k]}:{at(s)}:{at(e)}" for s, k, e in sorted(spans))

                    for _, k, _ in by.get(d, []):
                        counts[k, i + d] += 1
                    digests[i + d] = hashlib.sha256(points(by.get(d, [])).encode()).hexdigest()
                    lists[i + d] = points(by.get(d, []) + extra.get(d, []))
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(c) for c in counts), pa.array(digests, pa.string()), pa.array(lists, pa.string())], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    return run


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", formats: Formats | None = None, **options) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans (kind:start:end in code points, by start, then kind).

    formats: learned before, or else learned from the same table with the options of infer_formats.
    """
    learned = formats or infer_formats(docs, text_col, **options)
    ship(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(_scan(learned), "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def redact(text: str, spans: str, mask: str = "[REDACTED]") -> str:
    """text with every span replaced; overlapping spans are one."""
    out, at = [], 0
    for s, e in sorted((int(x.split(":")[1]), int(x.split(":")[2])) for x in spans.split(",") if x):
        if s >= at:
            out += [text[at:s], mask]
        at = max(at, e)
    return "".join(out) + text[at:]
