"""Document quality from a linear-chain conditional random field over lines.

Every line is good or bad. A line's features are shares of byte classes, word shapes and how much of
it the document has said before, together with the same features of the lines before and after;
two transition weights tie neighbouring labels. Labels of documents are the labels of their
lines in training. A document's score is the mean, weighted by line length, of the forward-backward
probability that a line is good.

Training uses at most `max_docs` labelled documents (those of smallest hash; the bound is a
parameter, so what the driver holds does not grow with the table); their line features, not their
texts, come to the driver. Scoring is one pass over whole texts.

Defined cases: null text is empty, and an empty text is one empty line; rows without a label are
scored like others; a null id is never held out and never a training row; with no label of either class, or no bad one,
every score is 1, and with no good one 0; an empty table gives an empty result.
"""

from __future__ import annotations

import json
from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .common import SpanHash, byte_hash, chunks, ship, text_buffer, word_spans

_CLASSES = {
    "upper": b"ABCDEFGHIJKLMNOPQRSTUVWXYZ",
    "lower": b"abcdefghijklmnopqrstuvwxyz",
    "vowel": b"aeiouAEIOU",
    "digit": b"0123456789",
    "stop": b".,;:",
    "shout": b"!?",
    "sign": b"#$%&*+/<=>@\\^_`~",
    "rule": b"|{}[]()\"'-",
    "blank": b" \t\r\x0b\x0c",
}
_MASKS = {k: np.isin(np.arange(256), list(v)) for k, v in _CLASSES.items()}
_MASKS["beyond"] = np.arange(256) >= 0x80
#: Features of a line by itself.
N_OWN = len(_MASKS) + 8


def line_features(flat: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(features, document, bytes) of each line of a chunk of documents, in order."""
    n = len(flat)
    breaks = np.flatnonzero(flat == 0x0A)
    begin = np.concatenate([offsets[:-1], breaks + 1])
    owner = np.concatenate([np.arange(len(offsets) - 1), np.searchsorted(offsets, breaks, side="right") - 1])
    order = np.lexsort((begin, owner))
    begin, owner = begin[order], owner[order]
    last = np.append(owner[1:] != owner[:-1], True)
    end = np.where(last, offsets[1:][owner], np.append(begin[1:], n) - 1)
    size = (end - begin).astype(float)
    safe = np.maximum(size, 1.0)
    x = np.zeros((len(begin), N_OWN))

    def inside(mask: np.ndarray) -> np.ndarray:
        sums = np.concatenate([[0], np.cumsum(mask)])
        return sums[end] - sums[begin]

    for k, mask in enumerate(_MASKS.values()):
        x[:, k] = inside(mask[flat]) / safe
    k = len(_MASKS)
    start, stop, doc = word_spans(flat, offsets)
    line = np.searchsorted(begin, start, side="right") - 1
    # documents without bytes share their start with the next line: step to the line that holds the word
    n_words = np.bincount(line, minlength=len(begin)).astype(float)
    chars = np.bincount(line, weights=(stop - start).astype(float), minlength=len(begin))
    words = np.maximum(n_words, 1.0)
    name = byte_hash(flat, 1).of(start, stop)

    def share_of_new(names: np.ndarray, where: np.ndarray, docs: np.ndarray) -> np.ndarray:
        """Per line, the share of items that the document has not had before."""
        if not len(names):
            return np.ones(len(begin))
        order = np.lexsort((np.arange(len(names)), names, docs))
        fresh = np.ones(len(names), bool)
        fresh[1:] = (names[order][1:] != names[order][:-1]) | (docs[order][1:] != docs[order][:-1])
        new = np.zeros(len(names))
        new[order] = fresh
        total = np.bincount(where, minlength=len(begin)).astype(float)
        return np.where(total > 0, np.bincount(where, weights=new, minlength=len(begin)) / np.maximum(total, 1.0), 1.0)

    x[:, k] = np.log1p(size) / 10
    x[:, k + 1] = np.log1p(n_words) / 8
    x[:, k + 2] = np.minimum(chars / words, 40) / 10
    x[:, k + 3] = share_of_new(name, line, doc)
    three = np.flatnonzero(doc[2:] == doc[:-2]) if len(doc) > 2 else np.zeros(0, np.int64)
    x[:, k + 4] = share_of_new(SpanHash(name, 2).of(three, three + 3), line[three], doc[three])
    x[:, k + 5] = np.bincount(line, weights=_MASKS["upper"][flat[start]].astype(float) if len(start) else None, minlength=len(begin)) / words
    tail = flat[stop - 1] if len(stop) else np.zeros(0, np.uint8)
    odd = _MASKS["sign"][tail] | _MASKS["shout"][tail]
    x[:, k + 6] = np.bincount(line, weights=odd.astype(float), minlength=len(begin)) / words
    x[:, k + 7] = np.bincount(line, weights=((stop - start) == 1).astype(float), minlength=len(begin)) / words
    return x, owner, size


def with_neighbours(x: np.ndarray, doc: np.ndarray) -> np.ndarray:
    """Own features, those of the line before and of the line after (zeros at the ends), and a constant."""
    before, after = np.zeros_like(x), np.zeros_like(x)
    if len(x) > 1:
        same = (doc[1:] == doc[:-1])[:, None]
        before[1:] = np.where(same, x[:-1], 0)
        after[:-1] = np.where(same, x[1:], 0)
    return np.concatenate([x, before, after, np.ones((len(x), 1))], axis=1)


class Chains:
    """Documents as chains of lines, worked on in step: position 0 of all, then position 1 of those that have it."""

    def __init__(self, doc: np.ndarray):
        self.start = np.flatnonzero(np.append(True, doc[1:] != doc[:-1])) if len(doc) else np.zeros(0, np.int64)
        length = np.diff(np.append(self.start, len(doc)))
        order = np.argsort(-length, kind="stable")
        self.start, self.length = self.start[order], length[order]

    def steps(self) -> Iterator[np.ndarray]:
        for t in range(int(self.length.max(initial=0))):
            live = int(np.searchsorted(-self.length, -t, side="left"))
            yield self.start[:live] + t

    def forward_backward(self, score: np.ndarray, move: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        """(probability that each line is good, expected transitions, log normaliser). score: of good against bad; move: 2 x 2 log weights."""
        unary = np.stack([np.zeros(len(score)), score], axis=1)
        alpha, beta = np.zeros_like(unary), np.zeros_like(unary)
        steps = list(self.steps())
        for t, rows in enumerate(steps):
            alpha[rows] = unary[rows]
            if t:
                prior = alpha[rows - 1]
                alpha[rows] += np.logaddexp(prior[:, [0]] + move[0], prior[:, [1]] + move[1])
        for t in range(len(steps) - 2, -1, -1):
            rows = steps[t + 1] - 1
            ahead = unary[rows + 1] + beta[rows + 1]
            beta[rows] = np.logaddexp(move[:, 0] + ahead[:, [0]], move[:, 1] + ahead[:, [1]])
        ends = self.start + self.length - 1
        z = np.logaddexp(alpha[ends, 0], alpha[ends, 1])
        both = alpha + beta
        good = 1.0 / (1.0 + np.exp(np.clip(both[:, 0] - both[:, 1], -700, 700)))
        pairs = np.zeros((2, 2))
        norm = np.empty(len(score))
        for t, rows in enumerate(steps):
            norm[rows] = z[: len(rows)]
        inner = np.concatenate([r for r in steps[1:]]) if len(steps) > 1 else np.zeros(0, np.int64)
        for a in (0, 1):
            for b in (0, 1):
                pairs[a, b] = np.exp(alpha[inner - 1, a] + move[a, b] + unary[inner, b] + beta[inner, b] - norm[inner]).sum() if len(inner) else 0.0
        return good, pairs, float(z.sum())


class LineField:
    """The fitted model: standardisation, line weights, transition weights; or a constant."""

    def __init__(self, constant: float | None = None):
        self.constant = constant

    def fit(self, x: np.ndarray, doc: np.ndarray, label: np.ndarray, rounds: int = 250, rate: float = 0.08, ridge: float = 2e-3) -> LineField:
        """x: line features with neighbours; label: of each line."""
        self.mean, self.sd = x.mean(axis=0), x.std(axis=0)
        self.mean[-1], self.sd[-1] = 0.0, 1.0
        self.sd[self.sd < 1e-9] = 1.0
        v = (x - self.mean) / self.sd
        chains = Chains(doc)
        y = label.astype(float)
        same = np.append(False, doc[1:] == doc[:-1])
        seen = np.zeros((2, 2))
        np.add.at(seen, (label[np.flatnonzero(same) - 1], label[np.flatnonzero(same)]), 1)
        n = max(1, len(chains.start))
        # a document counts once, however many lines it has
        w, move = np.zeros(v.shape[1]), np.zeros((2, 2))
        state = [np.zeros_like(w), np.zeros_like(w), np.zeros_like(move), np.zeros_like(move)]
        for k in range(1, rounds + 1):
            good, pairs, _ = chains.forward_backward(v @ w, move)
            grads = (v.T @ (good - y) / n + ridge * w, (pairs - seen) / n + ridge * move)
            for at, (g, p) in enumerate(zip(grads, (w, move), strict=True)):
                m, s = state[2 * at], state[2 * at + 1]
                m += 0.1 * (g - m)
                s += 0.01 * (g * g - s)
                p -= rate * (m / (1 - 0.9**k)) / (np.sqrt(s / (1 - 0.99**k)) + 1e-8)
        self.weights, self.move = w, move
        return self

    def lines(self, x: np.ndarray, doc: np.ndarray) -> np.ndarray:
        """Probability of each line to be good."""
        if self.constant is not None:
            return np.full(len(x), self.constant)
        v = (with_neighbours(x, doc) - self.mean) / self.sd
        return Chains(doc).forward_backward(v @ self.weights, self.move)[0]

    def documents(self, flat: np.ndarray, offsets: np.ndarray) -> np.ndarray:
        x, doc, size = line_features(flat, offsets)
        weight = size + 1.0
        n = len(offsets) - 1
        return np.bincount(doc, weights=weight * self.lines(x, doc), minlength=n) / np.bincount(doc, weights=weight, minlength=n)


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        flat, off = text_buffer(b.column(1))
        for i, j in chunks(off):
            a = off[i]
            x, doc, _ = line_features(flat[a : off[j]], off[i : j + 1] - a)
            at = np.searchsorted(doc, np.arange(j - i + 1))
            yield pa.RecordBatch.from_arrays([b.column(0).slice(i, j - i), pa.array([x[at[k] : at[k + 1]].astype(np.float32).tobytes() for k in range(j - i)], pa.binary())], names=["label", "lines"])


def crc_mod(id_col: str, parts: int) -> Column:
    return F.pmod(F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")), F.lit(parts).cast("long"))


def fit_line_field(docs: DataFrame, labels: DataFrame, label_col: str = "quality", id_col: str = "doc_id", text_col: str = "text", train_if: Column | None = None, max_docs: int = 4000) -> LineField:
    """Fits on the labelled rows of labels that satisfy train_if, max_docs of them at most."""
    ship(docs.sparkSession)
    rows = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull())
    if train_if is not None:
        rows = rows.where(train_if)
    chosen = rows.select(F.col(id_col).alias("__id"), F.col(label_col).cast("int").alias("label"), F.xxhash64(F.lit(3), id_col).alias("draw")).orderBy("draw", "label").limit(max_docs)
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    texts = rows.join(F.broadcast(chosen), F.col("id") == F.col("__id")).select("label", "text")
    got = texts.mapInArrow(_features, "label int, lines binary").collect()
    seen = {r.label for r in got}
    if len(seen) < 2:
        return LineField(0.0 if seen == {0} else 1.0)
    got.sort(key=lambda r: (r.label, r.lines))
    each = [np.frombuffer(r.lines, np.float32).reshape(-1, N_OWN).astype(float) for r in got]
    doc = np.repeat(np.arange(len(each)), [len(x) for x in each])
    label = np.repeat(np.array([r.label for r in got]), [len(x) for x in each])
    return LineField().fit(with_neighbours(np.concatenate(each), doc), doc, label)


def _score(model: LineField, text_at: int, keep: int):
    """Scores the column at text_at; the first `keep` columns go on."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat, off = text_buffer(b.column(text_at))
            for i, j in chunks(off):
                a = off[i]
                score = pa.array(np.clip(model.documents(flat[a : off[j]], off[i : j + 1] - a), 0.0, 1.0))
                part = b.slice(i, j - i)
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in range(keep)), score], names=[*b.schema.names[:keep], "score"])

    return run


def score_documents(docs: DataFrame, model: LineField, id_col: str = "doc_id", text_col: str = "text", with_rows: Sequence[str] | None = None) -> DataFrame:
    """doc_id, score of every document; or the columns with_rows, the text among them, as they came, and score, in the same pass."""
    ship(docs.sparkSession)
    rows = docs.select(*with_rows) if with_rows else docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    keep = rows.schema.fields if with_rows else rows.schema.fields[:1]
    text_at = list(with_rows).index(text_col) if with_rows else 1
    return rows.mapInArrow(_score(model, text_at, len(keep)), StructType([*keep, StructField("score", DoubleType())]))


_PARTS = ("mean", "sd", "weights", "move")


def to_text(model: LineField) -> str:
    """A fitted model as JSON; from_text reads it."""
    return json.dumps({"constant": model.constant, **({} if model.constant is not None else {k: getattr(model, k).tolist() for k in _PARTS})})


def from_text(text: str) -> LineField:
    held = json.loads(text)
    model = LineField(held["constant"])
    if model.constant is None:
        for k in _PARTS:
            setattr(model, k, np.array(held[k], float))
    return model
