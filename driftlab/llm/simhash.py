"""SimHash near-duplicates found through Golay-code fuzzy keys.

A fingerprint's 64 bits are cut into three segments (22, 21 and 21 bits), each read as a word of
the perfect binary Golay code of length 23 with zeros ahead. The keys of a segment are the codewords nearest to
the segment and to its 23 one-bit neighbours: one key if the segment lies within 2 of its
codeword, six if at 3. Two segments at most 2 bits apart share a word within one bit of both, so
they share a key. Two fingerprints at most 2 bits apart agree in at least one of the three
segments (pigeonhole), so a bucket is (segment number, the exact segment, one key of the next
segment): about 16 rows per distinct fingerprint, and no link is lost.

Buckets are verified without listing pairs of a large group: up to `small_bucket` members are compared
pairwise by popcount; in larger buckets each member names the 65 words within one bit of it, and
members that name the same word are linked to the smallest of them. Both are exact: two
fingerprints are at most 2 bits apart exactly if they name a common word, and distinct
fingerprints that name one word are at most 65.

Equal fingerprints are one node from the start. Components come from min_components over the
links between distinct fingerprints.

Defined cases: null text is empty and has fingerprint zero; rows repeated whole get the same
answer each; null identifiers get a component but are never one; an empty table gives an empty result.
"""

from __future__ import annotations

from bisect import bisect_right
from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import NO_ID, chunks, cut, min_components, mix64, ship, signed, stand_in, text_buffer

#: (lowest bit, width) of the three segments.
SEGMENTS = ((42, 22), (21, 21), (0, 21))
#: Generator polynomial of the [23, 12, 7] Golay code: x^11 + x^10 + x^6 + x^5 + x^4 + x^2 + 1.
GOLAY_POLY = 0b110001110101


def _remainder(words: np.ndarray) -> np.ndarray:
    """Polynomial remainder of 23-bit words: the syndrome."""
    r = words.astype(np.uint32)
    for bit in range(22, 10, -1):
        hit = (r >> np.uint32(bit)) & np.uint32(1)
        r = r ^ (hit * np.uint32(GOLAY_POLY << (bit - 11)))
    return r


@cache
def _leaders() -> np.ndarray:
    """The error pattern of at most 3 bits for each of the 2048 syndromes."""
    ones = [1 << i for i in range(23)]
    two = [a | b for i, a in enumerate(ones) for b in ones[:i]]
    three = [a | b for i, a in enumerate(ones) for b in two if b < a]
    words = np.array([0, *ones, *two, *three], np.uint32)
    table = np.zeros(2048, np.uint32)
    table[_remainder(words)] = words
    return table


def codeword_index(words: np.ndarray) -> np.ndarray:
    """12-bit index of the codeword nearest to each 23-bit word."""
    return (words ^ _leaders()[_remainder(words)]) >> np.uint32(11)


def golay_keys(words: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, key): the distinct codeword indices near each word."""
    flips = np.concatenate([[0], 1 << np.arange(23)]).astype(np.uint32)
    near = np.sort(codeword_index(words[:, None] ^ flips[None, :]), axis=1)
    fresh = np.ones(near.shape, bool)
    fresh[:, 1:] = near[:, 1:] != near[:, :-1]
    row, col = np.nonzero(fresh)
    return row, near[row, col]


def simhash_of(text: bytes, shingle: int = 3) -> int:
    """Fingerprint of a text: per bit, whether over half the shingle hashes (XXH64, seed 42) have it."""
    hashes = shingle_hashes(text, shingle)
    return _majority(hashes) if len(hashes) else 0


def _majority(hashes: np.ndarray) -> int:
    total = np.zeros(64, np.int64)
    for i in range(0, len(hashes), 1 << 14):
        part = hashes[i : i + (1 << 14)]
        total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(sum(1 << int(b) for b in np.flatnonzero(2 * total > len(hashes))))


def _fingerprints(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat, off = text_buffer(b.column(1))
            raw = flat.tobytes()
            held: dict[bytes, int] = {}  # copies inside one batch are hashed once
            out = np.zeros(len(off) - 1, np.uint64)
            for d in range(len(off) - 1):
                t = raw[off[d] : off[d + 1]]
                f = held.get(t)
                if f is None:
                    f = held[t] = simhash_of(t, shingle)
                out[d] = f
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(signed(out))], names=["doc_id", "fp"])

    return run


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """doc_id, fp (the 64 bits as a signed long)."""
    ship(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")).mapInArrow(_fingerprints(shingle), "doc_id long, fp long")


def _buckets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        ids = b.column(0).to_numpy(zero_copy_only=False)
        fp = b.column(1).to_numpy(zero_copy_only=False).view(np.uint64)
        seg = [((fp >> np.uint64(low)) & np.uint64((1 << width) - 1)).astype(np.uint32) for low, width in SEGMENTS]
        for k in range(3):
            row, key = golay_keys(seg[(k + 1) % 3])
            bucket = (np.uint64(k) << np.uint64(40)) | (seg[k][row].astype(np.uint64) << np.uint64(12)) | key.astype(np.uint64)
            yield pa.RecordBatch.from_arrays([pa.array(signed(bucket)), pa.array(ids[row]), pa.array(signed(fp[row]))], names=["bucket", "node", "fp"])


def near_links(nodes: DataFrame, small_bucket: int = 24, max_bits: int = 2) -> DataFrame:
    """(a, b): links between distinct fingerprints; nodes has node and fp, fp distinct. Linked nodes differ in at most 2 bits."""
    if max_bits != 2:
        raise ValueError("the keys are built for 2 bits")
    ship(nodes.sparkSession)
    rows = nodes.select("node", "fp").mapInArrow(_buckets, "bucket long, node long, fp long")
    dealt = cut(rows)
    sizes = dealt.groupBy("bucket").agg(F.count("*").alias("n")).where("n > 1")
    shared = dealt.join(sizes, "bucket")
    few = shared.where(F.col("n") <= small_bucket).groupBy("bucket").agg(F.collect_list(F.struct("node", "fp")).alias("m"))
    near = lambda x, y: F.bit_count(x["fp"].bitwiseXOR(y["fp"])) <= max_bits
    pairs = few.select(F.explode(F.flatten(F.transform("m", lambda x: F.transform(F.filter("m", lambda y: (y["node"] > x["node"]) & near(x, y)), lambda y: F.struct(x["node"].alias("a"), y["node"].alias("b")))))).alias("e")).select("e.a", "e.b")
    balls = F.expr("concat(array(fp), transform(sequence(0, 63), i -> fp ^ shiftleft(1L, i)))")
    many = shared.where(F.col("n") > small_bucket).select("node", "fp").distinct().select("node", F.explode(balls).alias("word"))
    meets = many.groupBy("word").agg(F.min("node").alias("a"), F.collect_list("node").alias("all")).where(F.size("all") > 1).select("a", F.explode("all").alias("b")).where("a <> b")
    return pairs.union(meets).distinct()


def near_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """doc_id, fingerprint (hex), component_id (smallest id reachable over links of at most 2 bits)."""
    prints = cut(fingerprints(docs, id_col, text_col, shingle))
    nodes = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("node")).where("node IS NOT NULL"))
    comp = min_components(near_links(nodes))
    of_fp = nodes.join(comp, "node", "left").select("fp", F.coalesce("component", "node").alias("component_id"))
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return prints.join(of_fp, "fp", "left").select("doc_id", hexed.alias("fingerprint"), "component_id")


def shingle_hashes(text: bytes, shingle: int) -> np.ndarray:
    """XXH64 (seed 42) of the lower-cased text's word shingles; of the whole sequence if it is shorter; none for no words."""
    words = text.lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    n = max(1, len(words) - shingle + 1)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    stops = ends[min(shingle, len(words)) - 1 :].tolist()
    starts = [0, *(ends[: n - 1] + 1).tolist()]
    return np.fromiter((xxhash.xxh64_intdigest(joined[i:j], 42) for i, j in zip(starts, stops, strict=True)), np.uint64, n)


@cache
def size_floors(similarity: float) -> list[int]:
    """Least sizes of the size classes: a set's partners at `similarity` lie in its own class, the one before or the one after."""
    floors = [1]
    while floors[-1] < 1 << 40:
        floors.append(int(floors[-1] / similarity + 1e-9) + 1)
    return floors


def most_apart(sizes: int, similarity: float) -> int:
    """Most elements in one of two sets only, if the sets have `sizes` elements together and Jaccard similarity `similarity` or more."""
    return int(sizes * (1 - similarity) / (1 + similarity) + 1e-9)


def part_prints(hashes: np.ndarray, similarity: float) -> list[int]:
    """Fingerprints of parts of a shingle set; two sets of Jaccard similarity `similarity` or more share at least one.

    A part is the shingles of one hash range. A class has more ranges than two of its sets can differ in
    elements, so some range holds the same in both. If a set has more filled ranges than it can differ from
    any partner, one of these is shared; else its empty ranges are parts as well. A set has the parts of
    its own size class and of the next, where it meets the larger partners.
    """
    kinds = np.unique(hashes)
    n = len(kinds)
    if not n:
        return [int(mix64(np.array([7], np.uint64))[0])]
    floors = size_floors(similarity)
    own = bisect_right(floors, n) - 1
    mixed = mix64(kinds)
    order = np.argsort(mixed)
    high, terms = (mixed[order] >> np.uint64(32)).astype(np.int64), mix64(kinds[order] ^ np.uint64(0x5851F42D4C957F2D))
    out: list[int] = []
    for level in (own, own + 1):
        most = floors[level + 1] - 1
        apart = most_apart(2 * most, similarity)
        cells = apart + 2 + apart // 6 if apart else 1
        cell = high * cells >> 32
        first = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))
        salt = np.uint64(level * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)
        number = cell[first].astype(np.uint64)
        tags = [mix64(np.add.reduceat(terms, first) + mix64(number + salt))]
        if len(first) <= most_apart(n + min(most, int(n / similarity + 1e-9)), similarity):
            tags.append(mix64(mix64(np.setdiff1d(np.arange(cells), cell[first]).astype(np.uint64) + salt)))
        out += np.concatenate(tags).tolist()
    return out


#: Most bits of a set's parity sketch.
SKETCH_MOST = 1 << 15


def parity_sketch(hashes: np.ndarray) -> np.ndarray:
    """Parity of the set's elements in each of a power of two of buckets, as 64-bit words.

    An element in one of two sets only flips one bit, so sketches differ in no more bits than the sets in
    elements; a sketch is halved by XOR of its halves.
    """
    kinds = np.unique(hashes)
    bits = min(SKETCH_MOST, max(64, 1 << (2 * len(kinds) - 1).bit_length() if len(kinds) else 64))
    at = (mix64(kinds ^ np.uint64(0x2545F4914F6CDD1D)) & np.uint64(bits - 1)).astype(np.int64)
    return np.packbits((np.bincount(at, minlength=bits) & 1).astype(np.uint8), bitorder="little").view(np.uint64)


def close_pairs(words: list[np.ndarray], kinds: np.ndarray, label: np.ndarray, side: np.ndarray, similarity: float) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs of different label, across the sides if there are two, that sizes and sketches do not rule out at `similarity`."""
    least = min(map(len, words))
    sketch = np.empty((len(words), least), np.uint64)
    for i, w in enumerate(words):
        while len(w) > least:
            w = w[: len(w) // 2] ^ w[len(w) // 2 :]
        sketch[i] = w
    left, right = np.flatnonzero(side == side.min()), np.flatnonzero(side == side.max())
    ratio = (1 - similarity) / (1 + similarity)
    found: list[tuple[np.ndarray, np.ndarray]] = []
    for i in left.tolist():
        js = right[right > i] if side[i] == side.max() else right
        js = js[label[js] != label[i]]
        if not len(js):
            continue
        room = (kinds[i] + kinds[js]) * ratio + 1e-9
        js, room = js[np.abs(kinds[js] - kinds[i]) <= room], room[np.abs(kinds[js] - kinds[i]) <= room]
        gap = np.bitwise_count(sketch[js] ^ sketch[i]).sum(axis=1, dtype=np.int64)
        js = js[gap <= room]
        if len(js):
            found.append((np.full(len(js), i), js))
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])


def _close(similarity: float):
    """Rows sorted by (part, low, high) to pairs of close_pairs in each such block."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []

        def pairs(t: pa.Table) -> Iterator[pa.RecordBatch]:
            ids, label, kinds, side = (t.column(c).to_numpy() for c in ("doc_id", "label", "kinds", "side"))
            words = [np.array(w, np.int64).view(np.uint64) for w in t.column("sketch").to_pylist()]
            i, j = close_pairs(words, kinds.astype(np.int64), label, side, similarity)
            for k in range(0, len(i), 10000):
                x, y = i[k : k + 10000], j[k : k + 10000]
                yield pa.RecordBatch.from_arrays([pa.array(ids[x]), pa.array(ids[y]), pa.array(label[x]), pa.array(label[y])], names=["a", "b", "la", "lb"])

        for b in batches:
            if not b.num_rows:
                continue
            keys = np.stack([b.column(b.schema.get_field_index(c)).to_numpy().astype(np.int64) for c in ("part", "low", "high")], axis=1)
            if held:
                last = held[-1]
                end = [last.column(last.schema.get_field_index(c))[last.num_rows - 1].as_py() for c in ("part", "low", "high")]
                if end != keys[0].tolist():
                    yield from pairs(pa.Table.from_batches(held))
                    held = []
            starts = [0, *(np.flatnonzero((keys[1:] != keys[:-1]).any(axis=1)) + 1).tolist(), b.num_rows]
            for s, e in zip(starts[:-1], starts[1:], strict=True):
                held.append(b.slice(s, e - s))
                if e < b.num_rows:
                    yield from pairs(pa.Table.from_batches(held))
                    held = []
        if held:
            yield from pairs(pa.Table.from_batches(held))

    return run


def _prints(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat, off = text_buffer(b.column(1))
            raw = flat.tobytes()
            prints, kinds, sketches = [], [], []
            for d in range(b.num_rows):
                h = shingle_hashes(raw[off[d] : off[d + 1]], shingle)
                prints.append(_majority(h) if len(h) else 0)
                kinds.append(len(np.unique(h)))
                sketches.append(signed(parity_sketch(h)))
            arrays = [b.column(0), pa.array(signed(np.array(prints, np.uint64))), pa.array(kinds, pa.int64()), pa.array(sketches, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "fp", "kinds", "sketch"])

    return run


def _parts(shingle: int, similarity: float):
    """(doc_id, part), each once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column(0).to_numpy(zero_copy_only=False)
            flat, off = text_buffer(b.column(1))
            raw = flat.tobytes()
            for i, j in chunks(off):
                parts = [np.unique(np.array(part_prints(shingle_hashes(raw[off[d] : off[d + 1]], shingle), similarity), np.uint64)) for d in range(i, j)]
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids[i:j], [len(p) for p in parts])), pa.array(signed(np.concatenate(parts)))], names=["doc_id", "part"])

    return run


def sketch_gap(x: np.ndarray, y: np.ndarray) -> int:
    """Bits in which two parity sketches differ, the larger one halved to the size of the other."""
    while len(x) > len(y):
        x = x[: len(x) // 2] ^ x[len(x) // 2 :]
    while len(y) > len(x):
        y = y[: len(y) // 2] ^ y[len(y) // 2 :]
    return int(np.bitwise_count(x ^ y).sum())


def _possible(similarity: float):
    """Of rows (a, b, kinds and sketches of both), the pairs that sizes and sketches do not rule out."""
    ratio = (1 - similarity) / (1 + similarity)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            get = lambda n, b=b: b.column(b.schema.get_field_index(n))
            ka, kb = get("ka").to_numpy(), get("kb").to_numpy()
            room = (ka + kb) * ratio + 1e-9
            near = np.flatnonzero(np.abs(ka - kb) <= room)
            (xo, xv), (yo, yv) = ((c.offsets.to_numpy(), c.values.to_numpy()) for c in (get("sa"), get("sb")))
            keep = [i for i in near.tolist() if sketch_gap(xv[xo[i] : xo[i + 1]].view(np.uint64), yv[yo[i] : yo[i + 1]].view(np.uint64)) <= room[i]]
            yield b.take(pa.array(keep, pa.int64())).select(["a", "b"])

    return run


def _sets(shingle: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat, off = text_buffer(b.column(1))
            raw = flat.tobytes()
            sets = [signed(np.unique(shingle_hashes(raw[off[d] : off[d + 1]], shingle))) for d in range(b.num_rows)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sets, pa.list_(pa.int64()))], names=["doc_id", "shingles"])

    return run


def _verified(texts: DataFrame, asked: DataFrame, shingle: int, similarity: float) -> DataFrame:
    """The rows of asked (a, b and others) whose documents' shingle sets have the similarity."""
    involved = asked.select(F.explode(F.array("a", "b")).alias("doc_id")).distinct()
    sets = cut(texts.join(involved, "doc_id", "left_semi").mapInArrow(_sets(shingle), "doc_id long, shingles array<long>"))
    left = sets.select(F.col("doc_id").alias("a"), F.col("shingles").alias("x"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("shingles").alias("y"))
    common = F.size(F.array_intersect("x", "y"))
    alike = common >= F.lit(similarity) * (F.size("x") + F.size("y") - common)
    return asked.join(left, "a").join(right, "b").where(alike).select(*asked.columns)


def similar_components(docs: DataFrame, shingle: int = 5, similarity: float = 0.8, id_col: str = "doc_id", text_col: str = "text", small_group: int = 16, block: int = 512) -> DataFrame:
    """doc_id, component_id: documents whose sets of word shingles have Jaccard similarity of `similarity` or more are linked.

    Rows without an id take part as documents of larger id than all others, one for each text; they come out, and stand as a component, as null.

    Every pair at the similarity shares a part fingerprint (part_prints), and every candidate that sizes and parity sketches do not
    rule out (which they never do at the similarity) is verified on the whole shingle sets, so the components are those of brute force. A group of up to small_group documents with
    one part is paired off. In a larger one each document first meets the smallest and its neighbour by id,
    and documents whose SimHash fingerprints differ in at most 2 bits (Golay keys) meet; then all pairs that these links
    left in different components are compared by sizes and parity sketches, in blocks of about `block` documents
    against each other, and what the sketches do not rule out is verified.
    """
    real = lambda c: F.when(F.col(c) < NO_ID, F.col(c)).alias(c)
    return _components(docs, shingle, similarity, id_col, text_col, small_group, block).select(real("doc_id"), real("component_id"))


def _components(docs: DataFrame, shingle: int, similarity: float, id_col: str, text_col: str, small_group: int = 16, block: int = 512) -> DataFrame:
    """similar_components with stand-ins for the ids that are null."""
    ship(docs.sparkSession)
    texts = docs.select(stand_in(id_col, text_col), F.col(text_col).cast("string").alias("text"))
    prints = cut(texts.mapInArrow(_prints(shingle), "doc_id long, fp long, kinds long, sketch array<long>"))
    # hashed a second time rather than written: most parts are met once
    rows = texts.mapInArrow(_parts(shingle, similarity), "doc_id long, part long")
    shared = cut(rows.withColumn("n", F.count("*").over(Window.partitionBy("part"))).where("n > 1"))
    few = shared.where(F.col("n") <= small_group).groupBy("part").agg(F.collect_list("doc_id").alias("m"))
    pairs = few.select(F.explode(F.expr("flatten(transform(m, x -> transform(filter(m, y -> y > x), y -> struct(x AS a, y AS b))))")).alias("e")).select("e.a", "e.b")
    many = shared.where(F.col("n") > small_group)
    lows = many.groupBy("part").agg(F.min("doc_id").alias("a"))
    beside = many.join(lows, "part").select("a", F.col("doc_id").alias("b"))
    next_to = many.select(F.lag("doc_id").over(Window.partitionBy("part").orderBy("doc_id")).alias("a"), F.col("doc_id").alias("b")).where("a IS NOT NULL")
    nodes = cut(prints.groupBy("fp").agg(F.min("doc_id").alias("node")))
    same = prints.join(nodes, "fp").select(F.col("node").alias("a"), F.col("doc_id").alias("b"))
    asked = pairs.union(beside).union(next_to).union(same).union(near_links(nodes)).where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    asked = asked.distinct()
    of = lambda side: prints.select(F.col("doc_id").alias(side), F.col("kinds").alias(f"k{side}"), F.col("sketch").alias(f"s{side}"))
    possible = asked.join(of("a"), "a").join(of("b"), "b").mapInArrow(_possible(similarity), "a long, b long").distinct()
    comp = cut(min_components(_verified(texts, cut(possible), shingle, similarity).select("a", "b")))
    labels = comp.select(F.col("node").alias("doc_id"), F.col("component").alias("found"))
    hot = many.join(labels, "doc_id", "left").select("part", "doc_id", "n", F.coalesce("found", "doc_id").alias("label"))
    split = hot.groupBy("part").agg(F.min("label").alias("l"), F.max("label").alias("h")).where("l < h").select("part")
    sketched = hot.join(split, "part").join(prints.select("doc_id", "kinds", "sketch"), "doc_id")
    blocks = F.ceil(F.col("n") / block).cast("int")
    dealt = sketched.withColumn("side", F.pmod(F.xxhash64("doc_id", F.lit(3)), blocks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    dealt = dealt.select("part", F.least("side", "other").alias("low"), F.greatest("side", "other").alias("high"), "side", "doc_id", "label", "kinds", "sketch")
    close = dealt.repartition("part", "low", "high").sortWithinPartitions("part", "low", "high").mapInArrow(_close(similarity), "a long, b long, la long, lb long")
    close = cut(close.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "la", "lb").dropDuplicates(["a", "b"]))
    found = prints.select("doc_id").join(labels, "doc_id", "left").select("doc_id", F.coalesce("found", "doc_id").alias("component_id"))
    if close.isEmpty():
        return found
    merged = min_components(_verified(texts, close, shingle, similarity).select(F.col("la").alias("a"), F.col("lb").alias("b")))
    return found.join(merged.withColumnRenamed("node", "component_id"), "component_id", "left").select("doc_id", F.coalesce("component", "component_id").alias("component_id"))


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """docs with one document of each component of similar_components: the one of smallest id, one without an id only where none has any; columns as they came. Rows that repeat an id stay or go together."""
    found = _components(docs, shingle, similarity, id_col, text_col)
    gone = found.where("doc_id <> component_id").select(F.col("doc_id").alias("__gone")).distinct()
    marked = docs.withColumn("__own", stand_in(id_col, text_col))
    return marked.join(gone, marked["__own"] == gone["__gone"], "left_anti").drop("__own")
