"""SentencePiece segmentation: k distinct sampled segmentations of every text, and decoding.

A text (with the model's leading blank) is cut before every run of blanks; no piece crosses such a
cut, so the lattice of a text is the chain of the lattices of its tokens, and a token's lattice is
built once per distinct token. Backward sums over the lattice give every arc its exact probability.

Sampling without replacement follows the Gumbel-max trick as a best-first search whose bound is
exact: the space of all segmentations has a Gumbel variable for its maximum; drawing the
maximiser along the lattice splits the rest of the space by the first arc that differs, each
part's maximum is a Gumbel variable of that part's mass truncated at the parent's maximum, and the
part of largest maximum is opened next. The first k maximisers are k distinct samples in order; the
(k+1)-th maximum is the threshold kappa of the inclusion scores 1 - exp(-exp(log p - kappa)). All
texts of a chunk are searched in step. Random numbers are hashes of the seed, the row's id and the
place in the text, so a rerun, a retried task or another partitioning gives the same samples.

Models whose scores are merge ranks (byte-pair vocabularies) get Zipf weights 1 / (rank + shift);
models with log probabilities are used as they are. Characters without a piece fall back to byte pieces.
Blanks inside a text are kept as they are and a literal U+2581 is written in byte pieces, so decoding
returns the text exactly; every chunk is decoded and compared before it leaves the task.

Defined cases: null and empty texts have one segmentation, of no pieces; a text with fewer than k
segmentations gives all of them, with inclusion score 1; null ids draw by their text; repeated
rows get the same samples; an empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import byte_hash, chunks, mix64, ship, signed, text_buffer, token_names

_U = np.uint64
MODEL = "/opt/tokenizers/piece_bpe_32k.model"
_BLANK = 0x20
_ONE = 1 << 30
_UNIT = float(1 << 32)
#: Bytes of text searched at once.
CHUNK = 1 << 20
#: Lattice nodes that a worker keeps between chunks.
CACHE_NODES = 1_500_000


def load_vocabulary(path: str = MODEL, shift: float = 10.0) -> dict:
    """Pieces (bytes, with blanks for U+2581), their ids and log weights, and the ids of the 256 byte pieces."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    n = model.get_piece_size()
    byte_ids = [-1] * 256
    ids, pieces, scores = [], [], []
    for i in range(n):
        if model.is_byte(i):
            byte_ids[int(model.id_to_piece(i)[3:5], 16)] = i
        elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)):
            ids.append(i)
            pieces.append(model.id_to_piece(i).replace("▁", " ").encode())
            scores.append(model.get_score(i))
    if min(byte_ids) < 0:
        raise ValueError("the model has no byte pieces")
    score = np.array(scores)
    ranks = bool(len(score)) and score.min() < -1000
    weight = -np.log(-score + shift) if ranks else score
    return {"ids": ids, "pieces": pieces, "weights": weight.tolist(), "byte_ids": byte_ids, "byte_weight": float(weight.min()) - 2.0, "size": n}


class Lattices:
    """Lattices of distinct tokens as one graph: arcs sorted by source node, with cumulative probabilities."""

    def __init__(self, vocabulary: dict):
        self.v = vocabulary
        step: dict[int, int] = {}
        ends: list[int] = [-1]
        for k, piece in enumerate(vocabulary["pieces"]):
            at = 0
            for b in piece:
                nxt = step.get(at << 8 | b)
                if nxt is None:
                    nxt = step[at << 8 | b] = len(ends)
                    ends.append(-1)
                at = nxt
            ends[at] = k
        # a row of 256 next states for each state that has any; row 0 is of the others
        keys = np.fromiter(step.keys(), np.int64, len(step))
        inner, at = np.unique(keys >> 8, return_inverse=True)
        self.row = np.zeros(len(ends), np.int32)
        self.row[inner] = np.arange(1, len(inner) + 1)
        self.next = np.full((len(inner) + 1, 256), -1, np.int32)
        self.next[at + 1, keys & 255] = np.fromiter(step.values(), np.int64, len(step))
        self.ends = np.array(ends)
        # states behind one and two bytes, looked up without a search
        self.one = np.array([step.get(b, -1) for b in range(256)])
        self.two = np.full(1 << 16, -1)
        for b in np.flatnonzero(self.one >= 0).tolist():
            for c in range(256):
                self.two[b << 8 | c] = step.get(int(self.one[b]) << 8 | c, -1)
        self.weight = np.array(vocabulary["weights"])
        self.ids = np.array(vocabulary["ids"], np.int64)
        self.piece_size = np.array([len(p) for p in vocabulary["pieces"]])
        self.clear()

    def clear(self) -> None:
        self.room: dict[str, np.ndarray] = {}
        self.known = np.zeros(0, _U)
        self.base = np.zeros(0, np.int64)
        self.hits = np.zeros(0, np.int64)
        self.first = np.zeros(1, np.int32)  # first arc of each node, and the number of arcs
        self.last = np.zeros(0, bool)  # nodes that end a token
        self.dst = np.zeros(0, np.int32)
        self.piece = np.zeros(0, np.int32)
        self.p = np.zeros(0)
        self.mark = np.zeros(0, np.int32)

    @property
    def nodes(self) -> int:
        return len(self.first) - 1

    def starts(self, flat: np.ndarray, begin: np.ndarray, end: np.ndarray, name: np.ndarray) -> np.ndarray:
        """Start node of each token."""
        fresh, first, back = np.unique(name, return_index=True, return_inverse=True)
        if self.nodes > CACHE_NODES:
            self._shrink()
        at = np.searchsorted(self.known, fresh)
        new = np.ones(len(fresh), bool)
        inside = at < len(self.known)
        new[inside] = self.known[at[inside]] != fresh[inside]
        if new.any():
            self._add(flat, begin[first[new]], end[first[new]], fresh[new])
            at = np.searchsorted(self.known, fresh)
        self.hits[at] += 1
        return self.base[at][back]

    def _shrink(self) -> None:
        """Keeps the lattices of tokens that more than one chunk had; none, if those are too many themselves."""
        order = np.argsort(self.base)
        length = np.diff(np.append(self.base[order], self.nodes))
        stay = self.hits[order] > 1
        if length[stay].sum() > CACHE_NODES // 2:
            self.clear()
            return
        kept, size = order[stay], length[stay]
        begin = self.base[kept]
        start = np.cumsum(size) - size
        node = np.repeat(begin - start, size) + np.arange(int(size.sum()))
        arcs = np.diff(self.first)[node].astype(np.int64)
        first = np.concatenate([[0], np.cumsum(arcs)])
        arc = np.repeat(self.first[node] - first[:-1], arcs) + np.arange(int(first[-1]))
        moved = np.repeat(np.repeat(begin - start, size), arcs)
        self.dst = (self.dst[arc] - moved).astype(np.int32)
        self.piece, self.p, self.mark, self.first = self.piece[arc], self.p[arc], self.mark[arc], first.astype(np.int32)
        self.last, self.room = self.last[node], {}
        again = np.argsort(self.known[kept], kind="stable")
        self.known, self.base, self.hits = self.known[kept][again], start[again], self.hits[kept][again] // 2

    def _add(self, flat: np.ndarray, begin: np.ndarray, end: np.ndarray, name: np.ndarray) -> None:
        length = end - begin
        offset = np.concatenate([[0], np.cumsum(length)])
        place = np.repeat(begin - offset[:-1], length) + np.arange(offset[-1])
        text = flat[place].astype(np.int64)
        owner = np.repeat(np.arange(len(length)), length)
        stop = offset[1:][owner]
        heads = np.flatnonzero((text & 0xC0) != 0x80)
        sizes = char_sizes(heads, np.minimum(np.append(heads[1:], len(text)), stop[heads]) if len(heads) else heads, len(text))
        found = []
        alone = np.zeros(len(text) + 1, bool)
        at, state, depth = heads, np.zeros(len(heads), np.int64), 0
        while len(at):
            live = at + depth < stop[at]
            at, state = at[live], state[live]
            if depth == 0:
                nxt = self.one[text[at]]
            elif depth == 1:
                nxt = self.two[text[at] << 8 | text[at + 1]]
            else:
                nxt = self.next[self.row[state], text[at + depth]]
            good = nxt >= 0
            at, state = at[good], nxt[good]
            depth += 1
            ended = self.ends[state]
            done = ended >= 0
            found.append((at[done], depth, ended[done]))
            alone[at[done][sizes[at[done]] == depth]] = True
        # characters without a piece of their own: one arc over their bytes
        bare = heads[~alone[heads]]
        # node numbers: a token of n bytes has n + 1 nodes, the last without arcs
        n = int(offset[-1]) + len(length)
        number = np.arange(len(text)) + owner
        arcs = np.zeros(n + 1, np.int64)
        for src, _, _ in found:
            arcs[number[src] + 1] += 1
        arcs[number[bare] + 1] += 1
        first = np.cumsum(arcs)
        slot = first[:-1].copy()
        total = int(first[-1])
        dst, piece, weight = np.zeros(total, np.int64), np.full(total, -1, np.int64), np.zeros(total)
        for src, depth, ended in found:
            s = number[src]
            k = slot[s]
            slot[s] += 1
            dst[k], piece[k], weight[k] = s + depth, ended, self.weight[ended]
        s = number[bare]
        dst[slot[s]], piece[slot[s]], weight[slot[s]] = s + sizes[bare], -sizes[bare], self.v["byte_weight"] * sizes[bare]
        # log sums over the ways to the end, from the end of each token
        ahead = np.full(n, -np.inf)
        last = offset[1:] + np.arange(len(length))
        ahead[last] = 0.0
        longest = np.argsort(-length, kind="stable")
        count = arcs[1:]
        for back in range(1, int(length.max(initial=0)) + 1):
            node = last[longest[: int(np.searchsorted(-length[longest], -back, side="right"))]] - back
            node = node[count[node] > 0]
            value, r = np.full(len(node), -np.inf), 0
            some = np.arange(len(node))
            while len(some):
                k = first[node[some]] + r
                value[some] = np.logaddexp(value[some], weight[k] + ahead[dst[k]])
                r += 1
                some = some[count[node[some]] > r]
            ahead[node] = value
        source = np.repeat(np.arange(n), count)
        p = np.exp(weight + ahead[dst] - ahead[source])
        # cumulative probabilities of a node's arcs in 30 bits: whole numbers, the same in every chunk
        upto, node, r = p.copy(), np.flatnonzero(count > 1), 1
        while len(node):
            k = first[node] + r
            upto[k] += upto[k - 1]
            r += 1
            node = node[count[node] > r]
        mark = np.minimum(np.rint(upto * _ONE), _ONE).astype(np.int64)
        mark[first[1:][count > 0] - 1] = _ONE
        base = offset[:-1] + np.arange(len(length)) + self.nodes
        begun, node_0 = int(self.first[-1]), self.nodes
        self._append("dst", dst + node_0)
        self._append("piece", piece)
        self._append("p", p)
        self._append("mark", mark)
        self._append("first", first[1:] + begun)
        self._append("last", _marked(n, last))
        known, bases = np.concatenate([self.known, name]), np.concatenate([self.base, base])
        order = np.argsort(known, kind="stable")
        self.known, self.base = known[order], bases[order]
        self.hits = np.concatenate([self.hits, np.zeros(len(name), np.int64)])[order]

    def _append(self, name: str, values: np.ndarray) -> None:
        """Adds to one of the arrays, in a buffer that grows by halves."""
        have = getattr(self, name)
        n, need = len(have), len(have) + len(values)
        room = self.room.get(name)
        if room is None or len(room) < need:
            room = self.room[name] = np.empty(max(need + need // 2, 1 << 16), have.dtype)
            room[:n] = have
        room[n:need] = values
        setattr(self, name, room[:need])

    def arcs(self, node: int) -> range:
        return range(int(self.first[node]), int(self.first[node + 1]))

    def ends_at(self, node: np.ndarray) -> np.ndarray:
        """Whether a node is its token's end."""
        return self.last[node]

    def source(self, arc: int) -> int:
        return int(np.searchsorted(self.first, np.int32(arc), side="right")) - 1

    def pick(self, node: np.ndarray, u: np.ndarray) -> np.ndarray:
        """The arc of each node that a number in [0, 1) chooses."""
        arc, at = self.first[node].astype(np.int64), (u * _ONE).astype(np.int32)
        open_ = np.flatnonzero(at >= self.mark[arc])
        while len(open_):
            arc[open_] += 1
            open_ = open_[at[open_] >= self.mark[arc[open_]]]
        return arc


def _marked(n: int, at: np.ndarray) -> np.ndarray:
    out = np.zeros(n, bool)
    out[at] = True
    return out


def char_sizes(heads: np.ndarray, after: np.ndarray, n: int) -> np.ndarray:
    """Bytes of the character that starts at each place."""
    out = np.zeros(n + 1, np.int64)
    out[heads] = after - heads
    return out


def uniform(*parts: np.ndarray) -> np.ndarray:
    """Numbers in (0, 1) that hash their arguments."""
    with np.errstate(over="ignore"):
        x = np.asarray(parts[0], _U)
        for p in parts[1:]:
            x = mix64(x + np.asarray(p).astype(_U) * _U(0x9E3779B97F4A7C15))
    return ((x >> _U(11)).astype(float) + 0.5) * 2.0**-53


def truncated(mass: np.ndarray, bound: np.ndarray, u: np.ndarray) -> np.ndarray:
    """A Gumbel variable of the given log mass, given that it is below the bound."""
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(np.isneginf(mass), -np.inf, mass - np.log(np.exp(np.minimum(mass - bound, 700.0)) - np.log(u)))


class Search:
    """The segmentations of one chunk of texts, searched in step."""

    def __init__(self, lattices: Lattices, flat: np.ndarray, offsets: np.ndarray, row_keys: np.ndarray):
        self.g, self.row_keys = lattices, row_keys
        n = len(offsets) - 1
        full = np.diff(offsets) > 0
        # the leading blank of every text that is not empty
        extra = np.cumsum(np.append(0, full))
        self.offsets = offsets + extra
        self.flat = np.full(int(self.offsets[-1]), _BLANK, np.uint8)
        keep = np.ones(len(self.flat), bool)
        keep[self.offsets[:-1][full]] = False
        self.flat[keep] = flat
        blank = self.flat == _BLANK
        lead = blank.copy()
        lead[1:] &= ~blank[:-1]
        lead[self.offsets[:-1][full]] = True
        self.begin = np.flatnonzero(lead)
        self.end = np.append(self.begin[1:], len(self.flat))
        self.doc = np.searchsorted(self.offsets, self.begin, side="right") - 1
        self.first = np.searchsorted(self.doc, np.arange(n + 1))
        self.n = n
        self.root = lattices.starts(self.flat, self.begin, self.end, token_names(self.flat, self.begin, self.end)) if len(self.begin) else np.zeros(0, np.int64)

    def draw(self, token: np.ndarray, node: np.ndarray, turn: int) -> tuple[np.ndarray, np.ndarray]:
        """Samples every token from its node on: (token, arc) in order of token, then place."""
        g = self.g
        key = self.row_keys[self.doc[token]]
        inner = token - self.first[self.doc[token]]
        who, took = [], []
        at, k = np.arange(len(token)), 0
        live = ~g.ends_at(node)
        at, node = at[live], node[live]
        while len(at):
            arc = g.pick(node, uniform(key[at], inner[at], turn, k))
            who.append(at)
            took.append(arc)
            node = g.dst[arc].astype(np.int64)
            live = ~g.ends_at(node)
            at, node = at[live], node[live]
            k += 1
        if not who:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        steps = np.zeros(len(token), np.int64)
        for w in who:
            steps[w] += 1
        first = np.cumsum(steps) - steps
        out = np.empty(int(steps.sum()), np.int64)
        for k, (w, arc) in enumerate(zip(who, took, strict=True)):
            out[first[w] + k] = arc
        return np.repeat(token, steps), out

    def run(self, k: int) -> tuple[list[list[dict]], np.ndarray]:
        """Per text up to k samples {paths, logp, value}; and each text's kappa."""
        g, n = self.g, self.n
        paths: list[dict] = []
        out: list[list[dict]] = [[] for _ in range(n)]
        kappa = np.full(n, -np.inf)
        token, arc = self.draw(np.arange(len(self.begin)), self.root, 0)
        value = -np.log(-np.log(uniform(self.row_keys, np.zeros(n), 7)))
        empty = np.diff(self.offsets) == 0
        start = np.zeros(n)
        paths.append(self._table(token, arc, np.arange(n), start, value, 0, None))
        for d in range(n):
            out[d].append({"path": 0, "value": float(value[d])})
        for turn in range(1, k + 1):
            best = np.stack([t["best"] for t in paths])
            pick = np.argmax(best, axis=0)
            value = best[pick, np.arange(n)]
            open_ = np.flatnonzero(~np.isneginf(value) & ~empty)
            if turn == k:
                kappa[open_] = value[open_]
                break
            tokens, nodes, begun, lead_arc = [], [], np.zeros(n), {}
            stop = np.zeros(n, np.int64)
            for d in open_.tolist():
                t = paths[pick[d]]
                j = t["at"][d]
                node = g.source(int(t["arc"][j]))
                out_arcs = t["barred"].setdefault(j, [int(t["arc"][j])])
                left = [e for e in g.arcs(node) if e not in out_arcs]
                weights = g.p[left]
                cut = np.cumsum(weights)
                e = left[int(min(np.searchsorted(cut, float(uniform(self.row_keys[d], j - t["first"][d], turn, 99)) * cut[-1], side="right"), len(left) - 1))]
                out_arcs.append(e)
                lead_arc[d] = e
                begun[d] = t["pre"][j] + np.log(g.p[e])
                tok = int(t["token"][j])
                tokens.append(tok)
                nodes.append(int(g.dst[e]))
                stop[d] = tok
                # what is left of this part
                mass = float(g.p[[x for x in left if x != e]].sum())
                t["v"][j] = float(truncated(np.array(t["pre"][j] + np.log(mass) if mass > 0 else -np.inf), value[d], uniform(self.row_keys[d], j - t["first"][d], turn, 98)))
                lo, hi = t["first"][d], t["first"][d + 1]
                at = lo + int(np.argmax(t["v"][lo:hi]))
                t["at"][d], t["best"][d] = at, t["v"][at]
                out[d].append({"path": turn, "value": float(value[d]), "parent": int(pick[d]), "step": int(j), "lead": e})
            # the tokens after the ones cut into
            some = open_
            rest = self.first[some + 1] - stop[some] - 1
            later = np.repeat(stop[some] + 1 - np.append(0, np.cumsum(rest)[:-1]), rest) + np.arange(int(rest.sum()))
            token = np.concatenate([np.array(tokens, np.int64), later])
            node = np.concatenate([np.array(nodes, np.int64), self.root[later]]) if len(later) else np.array(nodes, np.int64)
            order = np.argsort(token, kind="stable")
            token, arc = self.draw(token[order], node[order], turn)
            paths.append(self._table(token, arc, np.arange(n), begun, value, turn, lead_arc))
        self.paths = paths
        return out, kappa

    def _table(self, token: np.ndarray, arc: np.ndarray, docs: np.ndarray, start: np.ndarray, value: np.ndarray, turn: int, lead: dict | None) -> dict:
        """A path of every text: its arcs, log probability before each, and the maxima of the parts that leave it there."""
        g, n = self.g, self.n
        doc = self.doc[token] if len(token) else token
        first = np.searchsorted(doc, np.arange(n + 1))
        # in fixed point: a sum does not depend on what else is in the chunk
        total = np.concatenate([[0], np.cumsum(np.rint(np.log(g.p[arc]) * _UNIT).astype(np.int64))])
        pre = start[doc] + (total[:-1] - total[first[:-1]][doc]) / _UNIT if len(doc) else np.zeros(0)
        with np.errstate(divide="ignore"):
            mass = pre + np.log1p(-np.minimum(g.p[arc], 1.0))
        place = np.arange(len(doc)) - first[:-1][doc] if len(doc) else np.zeros(0)
        v = truncated(mass, value[doc], uniform(self.row_keys[doc], place, turn, 97)) if len(doc) else np.zeros(0)
        best, at = np.full(n, -np.inf), np.full(n, -1, np.int64)
        full = np.flatnonzero(np.diff(first))
        if len(full):
            best[full] = np.maximum.reduceat(v, first[:-1][full])
            hit = v == best[doc]
            hit_at = np.flatnonzero(hit)
            lead_hit = np.searchsorted(doc[hit_at], full)
            at[full] = hit_at[lead_hit]
        return {"token": token, "arc": arc, "pre": pre, "v": v, "first": first, "best": best, "at": at, "barred": {}, "end": start + (total[first[1:]] - total[first[:-1]]) / _UNIT}

    def arcs_of(self, d: int, sample: dict) -> np.ndarray:
        """All arcs of a sample."""
        t = self.paths[sample["path"]]
        own = t["arc"][t["first"][d] : t["first"][d + 1]]
        if "parent" not in sample:
            return own
        return np.concatenate([self._prefix(d, sample["parent"], sample["step"]), [sample["lead"]], own])

    def _prefix(self, d: int, path: int, step: int) -> np.ndarray:
        t = self.paths[path]
        own = t["arc"][t["first"][d] : step]
        made = next((s for s in self.samples[d] if s["path"] == path and "parent" in s), None)
        return own if made is None else np.concatenate([self._prefix(d, made["parent"], made["step"]), [made["lead"]], own])

    def segmentations(self, k: int) -> list[list[tuple[np.ndarray, float, float, float]]]:
        """Per text: (piece ids, log probability, perturbed value, inclusion score) of each sample; checked by decoding."""
        self.samples, kappa = self.run(k)
        byte_ids = np.array(self.g.v["byte_ids"])
        self.piece_size = self.g.piece_size
        out = []
        for d in range(self.n):
            rows = []
            text = self.flat[self.offsets[d] : self.offsets[d + 1]]
            for s in self.samples[d]:
                arcs = self.arcs_of(d, s)
                piece = self.g.piece[arcs]
                ids = self.g.ids[piece]
                bare = piece < 0
                if bare.any():
                    # the bytes of characters without a piece; the pieces' sizes tell where they are
                    size = np.where(bare, -piece, self.piece_size[piece])
                    n = np.where(bare, size, 1)
                    begin = np.cumsum(size) - size
                    inner = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
                    raw = np.repeat(bare, n)
                    ids = np.repeat(ids, n)
                    ids[raw] = byte_ids[text[(np.repeat(begin, n) + inner)[raw]]]
                logp = float(self.paths[s["path"]]["end"][d])
                score = 1.0 if np.isneginf(kappa[d]) else float(-np.expm1(-np.exp(min(logp - kappa[d], 700.0))))
                rows.append((ids, logp, s["value"], score))
            out.append(rows)
        return out


class Decoder:
    """Piece ids back to bytes."""

    def __init__(self, vocabulary: dict):
        table = [b""] * vocabulary["size"]
        for i, p in zip(vocabulary["ids"], vocabulary["pieces"], strict=True):
            table[i] = p
        for b, i in enumerate(vocabulary["byte_ids"]):
            table[i] = bytes([b])
        self.size = np.array([len(x) for x in table])
        self.start = np.concatenate([[0], np.cumsum(self.size)])
        self.body = np.frombuffer(b"".join(table), np.uint8)

    def bytes_of(self, ids: np.ndarray) -> np.ndarray:
        size = self.size[ids]
        end = np.cumsum(size)
        return self.body[np.repeat(self.start[ids] - (end - size), size) + np.arange(int(end[-1]) if len(end) else 0)]


_HELD: dict = {}


def _kept(broadcast) -> tuple[Lattices, Decoder]:
    """The worker's lattices, kept between tasks."""
    v = broadcast.value
    tag = hashlib.md5(repr((v["size"], v["byte_weight"], v["weights"][:3], v["weights"][-3:])).encode()).hexdigest()
    if _HELD.get("tag") != tag:
        _HELD.update(tag=tag, pair=(Lattices(v), Decoder(v)))
    return _HELD["pair"]


def _encode(broadcast, k: int, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lattices, decoder = _kept(broadcast)
        for b in batches:
            flat, off = text_buffer(b.column(1))
            ids = b.column(0)
            for i, j in chunks(off, CHUNK):
                a = off[i]
                part, inner = flat[a : off[j]], off[i : j + 1] - a
                own = ids.slice(i, j - i)
                key = own.fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64).view(_U)
                if own.null_count:
                    none = own.is_null().to_numpy(zero_copy_only=False)
                    key = np.where(none, byte_hash(part, 2).of(inner[:-1], inner[1:]), key)
                with np.errstate(over="ignore"):
                    key = mix64(key + mix64(np.array([seed], _U)))
                search = Search(lattices, part, inner, key)
                found = search.segmentations(k)
                for nth in range(k):
                    every = [rows[nth][0] for rows in found if len(rows) > nth]
                    want = np.concatenate([search.flat[search.offsets[d] : search.offsets[d + 1]] for d, rows in enumerate(found) if len(rows) > nth] or [np.zeros(0, np.uint8)])
                    got = decoder.bytes_of(np.concatenate(every).astype(np.int64)) if every else want
                    if not np.array_equal(got, want):
                        raise ValueError("a segmentation does not decode to its text")
                flat_ids = [ids for rows in found for ids, *_ in rows]
                inner_off = np.concatenate([[0], np.cumsum([len(x) for x in flat_ids])]).astype(np.int32)
                values = np.concatenate(flat_ids).astype(np.int32) if flat_ids else np.zeros(0, np.int32)
                outer = np.concatenate([[0], np.cumsum([len(rows) for rows in found])]).astype(np.int32)
                pieces = pa.ListArray.from_arrays(pa.array(outer), pa.ListArray.from_arrays(pa.array(inner_off), pa.array(values)))
                lists = [pa.ListArray.from_arrays(pa.array(outer), pa.array([r[c] for rows in found for r in rows], pa.float64())) for c in (1, 2, 3)]
                yield pa.RecordBatch.from_arrays([own, pieces, *lists], names=["doc_id", "samples", "log_p", "perturbed", "inclusion"])

    return run


def sample_segmentations(docs: DataFrame, k: int = 2, seed: int = 17, model: str = MODEL, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, samples (array of piece id arrays, best perturbed first), log_p, perturbed, inclusion (arrays along samples)."""
    spark = docs.sparkSession
    ship(spark)
    vocabulary = spark.sparkContext.broadcast(load_vocabulary(model))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(_encode(vocabulary, k, seed), "doc_id long, samples array<array<int>>, log_p array<double>, perturbed array<double>, inclusion array<double>")


def _decode(broadcast):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        decoder = _kept(broadcast)[1]
        for b in batches:
            texts = []
            for ids in b.column(1):
                if not ids.is_valid:
                    texts.append(None)
                    continue
                raw = decoder.bytes_of(ids.values.to_numpy(zero_copy_only=False).astype(np.int64)).tobytes()
                texts.append(raw[1:].decode("utf-8", errors="replace") if raw[:1] == b" " else raw.decode("utf-8", errors="replace"))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return run


def decode_pieces(rows: DataFrame, ids_col: str, model: str = MODEL, id_col: str = "doc_id") -> DataFrame:
    """doc_id, text: the texts of arrays of piece ids; a null array gives null, bytes that are no text give U+FFFD."""
    spark: SparkSession = rows.sparkSession
    ship(spark)
    vocabulary = spark.sparkContext.broadcast(load_vocabulary(model))
    return rows.select(F.col(id_col).cast("long").alias("doc_id"), F.col(ids_col).alias("ids")).mapInArrow(_decode(vocabulary), "doc_id long, text string")


def row_key(doc_id: int, seed: int = 17) -> int:
    """The number that seeds a row's draws."""
    with np.errstate(over="ignore"):
        return int(signed(mix64(np.array([doc_id], np.int64).view(_U) + mix64(np.array([seed], _U))))[0])
