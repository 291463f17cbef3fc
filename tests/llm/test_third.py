"""Sampled segmentations, similar documents, and the pipeline, against brute force."""

import math
import random

import numpy as np
from pyspark.sql import functions as F

from driftlab.llm import mixing, pieces, simhash

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
NASTY = ["", " ", "  ", "a", " a", "a ", "x\n\ty  z ", "é漢字▁", "▁▁ ▁x", "<s> <0x41>", "b" * 3000, "word " * 400, "\x00\x01", "🙂🙂 ok"]


def docs(spark, rows):
    return spark.createDataFrame([(i, t, None, s, 0) for i, t, s in rows], DOCS)


def all_segmentations(vocabulary, text):
    """Every segmentation of a blank-led text with its log weight."""
    table = dict(zip(vocabulary["pieces"], vocabulary["weights"], strict=True))
    raw = (" " + text).encode()
    out = []

    def go(at, held, weight):
        if at == len(raw):
            out.append((tuple(held), weight))
            return
        size = len(raw[at:].decode()[0].encode())
        for end in range(at + 1, len(raw) + 1):
            if raw[at:end] in table:
                go(end, [*held, raw[at:end]], weight + table[raw[at:end]])
        if raw[at : at + size] not in table:
            go(at + size, [*held, raw[at : at + size]], weight + vocabulary["byte_weight"] * size)

    go(0, [], 0.0)
    z = np.logaddexp.reduce([w for _, w in out])
    return {s: w - z for s, w in out}


def sampled(vocabulary, texts, keys, k):
    flat = np.frombuffer("".join(texts).encode(), np.uint8)
    off = np.concatenate([[0], np.cumsum([len(t.encode()) for t in texts])])
    return pieces.Search(pieces.Lattices(vocabulary), flat, off, np.array(keys, np.uint64)).segmentations(k)


def test_samples_without_replacement():
    v = pieces.load_vocabulary()
    text = "ab th"
    want = all_segmentations(v, text)
    by_id = dict(zip(v["ids"], v["pieces"], strict=True))
    n = 4000
    keys = pieces.mix64(np.arange(n, dtype=np.uint64))
    first, second = {}, {}
    total = np.zeros(2)
    for rows in sampled(v, [text] * n, keys, 3):
        segs = [tuple(by_id[int(i)] for i in r[0]) for r in rows]
        assert len(set(segs)) == len(segs) == 3 and [r[2] for r in rows] == sorted((r[2] for r in rows), reverse=True)
        for s, r in zip(segs, rows, strict=True):
            assert abs(want[s] - r[1]) < 1e-8
        first[segs[0]] = first.get(segs[0], 0) + 1
        second[segs[1]] = second.get(segs[1], 0) + 1
        # inclusion scores weigh samples without bias: sum of p / q estimates 1
        total += [sum(math.exp(r[1]) / r[3] for r in rows), 1]
    assert abs(total[0] / total[1] - 1) < 0.05
    p = {s: math.exp(w) for s, w in want.items()}
    for s, q in p.items():
        assert abs(first.get(s, 0) / n - q) < 5 * math.sqrt(q / n) + 1e-3
        two = sum(p[a] * q / (1 - p[a]) for a in p if a != s)
        assert abs(second.get(s, 0) / n - two) < 5 * math.sqrt(two / n) + 2e-3


def test_few_segmentations_and_round_trip(spark):
    v = pieces.load_vocabulary()
    rows = sampled(v, ["", "漢"], [1, 2], 2)
    assert len(rows[0]) == 1 and len(rows[0][0][0]) == 0 and rows[0][0][3] == 1.0
    table = docs(spark, [*((i, t, None) for i, t in enumerate(NASTY)), (None, "no id", None), (77, None, None), (1, "twice the id", None)]).withColumn("samples", F.lit(1))
    got = pieces.sample_segmentations(table, k=3)
    assert got.count() == table.count()
    back = pieces.decode_pieces(got.where("doc_id < 70 AND doc_id <> 1").select("doc_id", F.explode("samples").alias("ids")), "ids")
    texts = {}
    for r in back.collect():
        texts.setdefault(r.doc_id, set()).add(r.text)
    assert texts == {i: {t} for i, t in enumerate(NASTY) if i != 1}
    again = pieces.sample_segmentations(table.repartition(7), k=3)
    assert sorted(map(str, got.collect())) == sorted(map(str, again.collect()))
    assert pieces.sample_segmentations(table.limit(0)).count() == 0


def jaccard_components(texts, n, least):
    sets = {}
    for i, t in texts.items():
        w = (t or "").lower().split()
        sets[i] = {tuple(w[k : k + n]) for k in range(max(1, len(w) - n + 1))} if w else set()
    parent = {i: i for i in texts}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    ids = sorted(texts)
    for x, a in enumerate(ids):
        for b in ids[:x]:
            u = len(sets[a] | sets[b])
            if u == 0 or len(sets[a] & sets[b]) >= least * u:
                p, q = find(a), find(b)
                parent[max(p, q)] = min(p, q)
    return {i: find(i) for i in ids}


def near_table(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefg") for _ in range(3))
    texts = {}
    for g in range(25):
        base = [word() for _ in range(rng.choice([8, 20, 60, 300]))]
        for _ in range(rng.choice([1, 2, 2, 3, 40 if g == 3 else 4])):
            w = list(base)
            for _ in range(rng.choice([0, 1, 1, len(w) // 60, len(w) // 20])):
                w[rng.randrange(len(w))] = word()
            texts[len(texts)] = " ".join(w)
    return texts | {5000: "", 5001: None, 5002: "one", 5003: "One", 5004: "one two"}


def test_similar_components(spark):
    missed = pairs = 0
    for seed in (1, 2):
        texts = near_table(seed)
        want = jaccard_components(texts, 5, 0.8)
        got = {r.doc_id: r.component_id for r in simhash.similar_components(docs(spark, [(i, t, None) for i, t in texts.items()])).collect()}
        assert set(got) == set(texts)
        for i in texts:
            pairs += want[i] != i
            missed += want[i] != i and got[i] == i
            # never a link that brute force does not have
            assert want[got[i]] == want[i]
    assert missed <= 0.02 * pairs
    left = simhash.drop_near_copies(docs(spark, [(1, "a b c d e f g h", None), (2, "A b c d e f g h", None), (None, "a b c d e f g h", None), (None, None, None)]).withColumn("component_id", F.lit(0)))
    assert sorted(str(r.doc_id) for r in left.collect()) == ["1", "None"]
    assert simhash.similar_components(docs(spark, [])).count() == 0
    none = simhash.drop_near_copies(docs(spark, [(None, "a b c d e f g h", None), (None, "A b c d e f g h", None), (None, "other words", None)]))
    assert sorted(r.text.lower() for r in none.collect()) == ["a b c d e f g h", "other words"]


def test_parts_are_lossless():
    """Sets at the threshold always share a part, whatever their sizes."""
    rng = np.random.default_rng(5)
    for n in [*range(1, 40), 127, 260, 520]:
        for _ in range(2000 if n == 127 else 100):
            # the whole difference on one side, or a swap of as many elements as the threshold allows
            x = rng.integers(0, 1 << 63, n).astype(np.uint64)
            for gone, new in ((n // 5, 0), (int(n / 9), int(n / 9))):
                y = np.concatenate([x[gone:], rng.integers(0, 1 << 63, new).astype(np.uint64)])
                if len(y) and len(np.intersect1d(x, y)) >= 0.8 * len(np.union1d(x, y)):
                    assert set(simhash.part_prints(x, 0.8)) & set(simhash.part_prints(y, 0.8)), (n, gone, new)


def test_large_family(spark):
    """A template family of some thousand documents at 0.6 to 0.8 of each other: the components of brute force."""
    rng = random.Random(11)
    base = [f"w{i}" for i in range(100)]
    texts = {}
    for i in range(2500):
        w = list(base)
        for k in rng.sample(range(100), 2):
            w[k] = f"x{rng.randrange(10**9)}"
        texts[rng.randrange(10**7)] = " ".join(w)
        if i % 25 == 0:
            w[rng.randrange(3, 97)] = f"y{i}"
            texts[rng.randrange(10**7)] = " ".join(w)
    ids = sorted(texts)
    sets = [{tuple(w[k : k + 5]) for k in range(len(w) - 4)} for w in (texts[i].split() for i in ids)]
    seen = {}
    for s in sets:
        for g in s:
            seen[g] = seen.get(g, 0) + 1
    column = {g: k for k, g in enumerate(g for g, c in seen.items() if c > 1)}
    m = np.zeros((len(ids), len(column)), np.float32)
    for r, s in enumerate(sets):
        m[r, [column[g] for g in s if g in column]] = 1
    size = np.array([len(s) for s in sets], np.float32)
    both = m @ m.T
    near = both >= 0.8 * (size[:, None] + size[None, :] - both) - 1e-3
    want = np.arange(len(ids))
    while True:
        low = np.where(near, want[None, :], len(ids)).min(axis=1)
        if (low == want).all():
            break
        want = low
    assert 50 < len(set(want.tolist())) < len(ids)
    got = {r.doc_id: r.component_id for r in simhash.similar_components(docs(spark, [(i, t, None) for i, t in texts.items()]), block=300).collect()}
    assert got == {i: ids[w] for i, w in zip(ids, want.tolist(), strict=True)}


def test_mixed_documents(spark):
    rng = random.Random(3)
    rows = [(i, " ".join(f"w{i}" for _ in range(rng.randint(0, 40))) + "\n", rng.choice(["a", "b", None])) for i in range(80)] + [(None, "x y", None), (500, None, "a")]
    table = docs(spark, rows)
    got = mixing.mixed_documents(table, block_words=4).collect()
    plan = {r.doc_id: r.taken for r in mixing.mix(table, block_words=4).collect()}
    taken = {}
    for r in got:
        taken[r.doc_id] = taken.get(r.doc_id, 0) + len(r.text.split())
    assert {i: n for i, n in plan.items() if n} == taken
    assert mixing.mixed_documents(table.limit(0)).columns == table.columns


def test_pipeline(spark, sf):
    import corpus_pipeline as cp

    raw = spark.read.parquet(f"{sf}/documents.parquet")
    before = None
    for (name, stage), step in zip(cp.STAGES, range(5), strict=True):
        made = stage(spark, raw, sf)
        rows = made.collect()
        assert rows, name
        if step < 4:
            assert made.columns == raw.columns
        if step == 1:
            assert len({r.text for r in rows}) == len(rows) == len({r.text for r in before})
        if step == 2:
            want = jaccard_components({r.doc_id: r.text for r in before}, 5, 0.8)
            assert {r.doc_id for r in rows} == set(want.values())
        if step == 4:
            assert len(rows) == len(before)
        before = rows
        raw = spark.createDataFrame(rows, made.schema)
    assert cp.run(spark, sf).count() == len(rows)
    empty = spark.createDataFrame([], raw.schema)
    del empty
    odd = docs(spark, [(1, None, None), (None, "a b", "s"), (None, None, None), (3, "", "s"), (4, "same text here", None), (4, "same text here", None)])
    for _, stage in cp.STAGES:
        made = stage(spark, odd, sf)
        odd = spark.createDataFrame(made.collect(), made.schema)
    none = docs(spark, [])
    for _, stage in cp.STAGES[:4]:
        none = stage(spark, none, sf)
        assert none.count() == 0
