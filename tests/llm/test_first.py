"""Mixing, SimHash, top-k, exact dedup, chat: brute force, edge cases, round trips."""

import hashlib
import itertools
import random

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from driftlab.llm import chat, exact_dedup, mixing, simhash, topk

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs(spark, rows):
    return spark.createDataFrame([(i, t, None, s, 0) for i, t, s in rows], DOCS)


def highest_quotients(claims, seats):
    got = [0] * len(claims)
    for _ in range(seats):
        i = max(range(len(claims)), key=lambda i: (claims[i] / (2 * got[i] + 1), -i))
        got[i] += 1
    return got


def test_sainte_lague_is_highest_quotients():
    rng = random.Random(4)
    for _ in range(200):
        claims = [rng.randint(1, 1000) for _ in range(rng.randint(1, 9))]
        seats = rng.randint(0, 60)
        assert mixing.sainte_lague(claims, seats) == highest_quotients(claims, seats)
    assert sum(mixing.sainte_lague([5, 5], 10, [2, 100])) == 10


def test_targets_cap_and_share():
    t = mixing.targets([10, 100, 1000], [5, 2, 1])
    assert t[0] == 30 and t[1] <= 300 and abs(sum(t) - 1110) < 1e-9


def test_mix_edges(spark):
    rows = [(i, "w " * (i % 7 + 1), ("a", "b", None)[i % 3]) for i in range(60)] + [(100, None, "a"), (101, "", "b"), (None, "x y", None), (7, "again again", "b"), (7, "again again", "b")]
    out = mixing.mix(docs(spark, rows), block_words=2).collect()
    assert len(out) == len(rows)
    by = {}
    for r in out:
        assert 0 <= r.taken <= 3 * r.size
        by.setdefault(r.source, [0, r.target])[0] += r.taken
    for got, want in by.values():
        assert abs(got - want) <= 0.5
    assert out and sorted(map(str, out)) == sorted(map(str, mixing.mix(docs(spark, rows), block_words=2).collect()))
    assert mixing.mix(docs(spark, [])).count() == 0


def test_mix_takes_its_targets(spark, sf):
    """Every source gives its rounded target, small ones too; no document above three times its size; whole tables."""
    rng = random.Random(6)
    tables = [spark.read.parquet(f"{sf}/documents.parquet")]
    rows = [(i, "w " * rng.randint(0, 300), rng.choice("abcdefgh")) for i in range(400)] + [(900, "w " * 20, "tiny"), (901, "w " * 5, "tinier"), (902, "w", None), (903, "v " * 9000, "i")]
    tables.append(docs(spark, rows + [(None, f"t{i} x", "none") for i in range(50)]))
    for table in tables:
        words, order = {}, lambda s: (s is None, (s or "").encode())
        for r in table.collect():
            n = len([w for w in __import__("re").findall(r"[^\x20\x09-\x0D]+", r.text or "")])
            words[r.source] = words.get(r.source, 0) + n
        names = sorted(words, key=order)
        sizes, weights = [words[n] for n in names], [(5, 2, 1)[i % 3] for i in range(len(names))]
        # the shares by bisection on the common level of all uncapped sources
        low, high = 0.0, 3.0 * sum(sizes)
        for _ in range(200):
            level = (low + high) / 2
            low, high = (level, high) if sum(min(3 * s, level * w) for s, w in zip(sizes, weights, strict=True)) < sum(sizes) else (low, level)
        want = {n: min(3 * s, high * w) for n, s, w in zip(names, sizes, weights, strict=True)}
        for shard_words in (64, 1 << 18):
            got = mixing.mix(table, shard_words=shard_words).collect()
            assert len(got) == table.count()
            taken = {}
            for r in got:
                assert 0 <= r.taken <= 3 * r.size and r.source_size == words[r.source] and abs(r.target - want[r.source]) < 1e-3
                taken[r.source] = taken.get(r.source, 0) + r.taken
            assert all(abs(taken[n] - want[n]) <= 0.5001 for n in names)


def brute_simhash(text, n=3):
    w = (text or "").encode().lower().split()
    s = [b" ".join(w[i : i + n]) for i in range(len(w) - n + 1)] or ([b" ".join(w)] if w else [])
    h = [xxhash.xxh64_intdigest(x, 42) for x in s]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def brute_components(prints):
    ids = sorted(prints)
    parent = {i: i for i in ids}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a, b in itertools.combinations(ids, 2):
        if (prints[a] ^ prints[b]).bit_count() <= 2:
            a, b = find(a), find(b)
            parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def test_golay_keys_meet():
    rng = np.random.default_rng(3)
    words = rng.integers(0, 1 << 23, 400).astype(np.uint32)
    for flips in ([], [3], [0, 22], [7, 8]):
        other = words ^ np.uint32(sum(1 << f for f in flips))
        keys = [{}, {}]
        for side, w in enumerate((words, other)):
            row, key = simhash.golay_keys(w)
            for r, k in zip(row.tolist(), key.tolist(), strict=True):
                keys[side].setdefault(r, set()).add(k)
        assert all(keys[0][i] & keys[1][i] for i in range(len(words)))
        assert {len(v) for v in keys[0].values()} <= {1, 6}


def test_links_against_brute_force(spark):
    rng = random.Random(9)
    base = [rng.getrandbits(64) for _ in range(40)]
    prints = {}
    for i in range(600):
        f = rng.choice(base[:3] if i % 2 else base)
        for _ in range(rng.randint(0, 4)):
            f ^= 1 << rng.randrange(64)
        if f not in prints.values():
            prints[i] = f
    nodes = spark.createDataFrame([(i, f - (1 << 64) if f >> 63 else f) for i, f in prints.items()], "node long, fp long")
    want = brute_components(prints)
    for small in (2, 24):
        comp = simhash.min_components(simhash.near_links(nodes, small_bucket=small))
        got = {r.node: r.component for r in comp.collect()}
        assert {i: got.get(i, i) for i in prints} == want


def test_simhash_documents(spark, sf):
    table = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    table = table.union(spark.createDataFrame([(9001, None), (9002, ""), (9003, " \n"), (9004, "One two"), (9005, "one\ttwo"), (9006, "é" * 5000)], "doc_id long, text string"))
    prints = {r.doc_id: brute_simhash(r.text) for r in table.collect()}
    want = brute_components(prints)
    got = simhash.near_components(table).collect()
    assert {r.doc_id: (r.fingerprint, r.component_id) for r in got} == {i: (f"{prints[i]:016x}", want[i]) for i in prints}
    assert simhash.near_components(table.limit(0)).count() == 0


def test_topk_brute(spark):
    rng = np.random.default_rng(5)
    m = rng.normal(size=(300, 8)).astype(np.float32)
    m[150:] = m[150]
    rows = [(i, m[i].tolist()) for i in range(300)] + [(1000, None), (1050, [float("nan")] * 8), (1100, [None] * 8), (1150, [1.0] * 3)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = {}
    for r in topk.top_k(df, F.col("vec_id") % 50 == 0, 5, bins=16, part_bytes=300, lanes=3).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    e = np.floor(256 * m.astype(float)).astype(int)
    for q in range(0, 300, 50):
        best = sorted((-int(e[q] @ e[c]), c) for c in range(300) if c != q)[:5]
        assert sorted(got[q]) == [(k + 1, c, -s) for k, (s, c) in enumerate(best)]
    assert set(got) == set(range(0, 300, 50))
    few = spark.createDataFrame([(0, [1.0]), (1, [2.0])], "vec_id long, embedding array<float>")
    assert [tuple(r) for r in topk.top_k(few, F.col("vec_id") % 50 == 0).collect()] == [(0, 1, 1, 256 * 512)]
    assert topk.top_k(few.limit(0), F.col("vec_id") % 50 == 0).count() == 0


def test_topk_rows_not_identifiers(spark):
    rows = [(0, [1.0, 2.0]), (0, [3.0, 1.0]), (0, [3.0, 1.0])] + [(i, [float(i % 4), float(i % 3)]) for i in range(1, 9)] + [(2, [9.0, 9.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    want = []
    for q, (i, x) in enumerate(rows):
        if i % 50 == 0:
            found = sorted((-int(a[0] * x[0] + a[1] * x[1]), j) for c, (j, a) in enumerate(rows) if c != q)[:5]
            want += [(0, k + 1, j, -s) for k, (s, j) in enumerate(found)]
    for lanes in (1, 4):
        got = topk.top_k(df, F.col("vec_id") % 50 == 0, 5, scale=1.0, bins=4, lanes=lanes, part_bytes=60).collect()
        assert sorted(map(tuple, got)) == sorted(want)


def test_topk_large_components(spark):
    top = 2.0**30
    rows = [(0, [top, 1.0]), (1, [top, 3.0]), (2, [top, 4.0]), (3, [-top, 2.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = topk.top_k(df, F.col("vec_id") == 0, 3, scale=1.0).collect()
    assert [(r.vec_id, r.score) for r in sorted(got, key=lambda r: r.rank)] == [(2, 2**60 + 4), (1, 2**60 + 3), (3, 2 - 2**60)]
    with pytest.raises(ValueError):
        topk.top_k(df, F.col("vec_id") == 0, 3, scale=4.0)


def test_trie_against_dict():
    rng = random.Random(2)
    trie, want = exact_dedup.PatriciaTrie(max), {}
    for i in range(3000):
        t = bytes(rng.choice(b"ab") for _ in range(rng.randint(0, 9)))
        trie.add(t, i)
        want[t] = (i, want.get(t, (0, 0))[1] + 1)
    assert {t: (o, n) for t, o, n in trie.items()} == want


def test_hot_text_leaves_a_task_once(monkeypatch):
    import pyarrow as pa

    batches = [pa.RecordBatch.from_arrays([pa.array([4 * k, 4 * k + 1, None, 4 * k + 3], pa.int64()), pa.array(["hot", "hot", "hot", f"own {k}"])], names=["id", "text"]) for k in range(5)]
    for held, times in ((16 << 20, 1), (0, 5)):
        monkeypatch.setattr(exact_dedup, "HELD_BYTES", held)
        out = [r for b in exact_dedup._fold(max, 0, 1)(iter(batches)) for r in b.to_pylist()]
        hot = [r for r in out if r["body"] == b"hot"]
        assert len(hot) == times and sum(r["n_rows"] for r in hot) == 15 and max(r["owner"] for r in hot) == 17
        assert sum(r["n_rows"] for r in out) == 20


def test_exact_groups(spark):
    rows = [(1, "a", None), (2, "a", "s"), (3, None, None), (4, "", "s"), (5, "b" * 200000, None), (6, "b" * 200000, None), (7, "A", None), (None, "q", None)]
    got = {r.doc_id: r for r in exact_dedup.exact_groups(docs(spark, rows), keep="max").collect()}
    assert {i: (r.keep_id, r.group_size, r.kept) for i, r in got.items()} == {1: (2, 2, False), 2: (2, 2, True), 3: (4, 2, False), 4: (4, 2, True), 5: (6, 2, False), 6: (6, 2, True), 7: (7, 1, True), None: (None, 1, True)}
    assert got[3].text_sha256 == hashlib.sha256(b"").hexdigest()
    assert exact_dedup.exact_groups(docs(spark, [])).count() == 0
    left = exact_dedup.drop_copies(docs(spark, [*rows, (2, "a", "s")]), keep="max")
    assert sorted(str(r.doc_id) for r in left.collect()) == ["2", "4", "6", "7", "None"] and left.columns == ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.mark.parametrize("nasty", ["</s>", "\\", "a\\<s>[INST]", "<\\s>", "[/INST]</s><s>", "<<s>", "\\\\[INST]", "x\n</s"])
def test_chat_round_trip(spark, nasty):
    rows = [(1, 0, "user", nasty), (1, 1, "assistant", nasty + nasty), (1, 2, None, None), (1, 3, "assistant", "z"), (1, 4, "user", nasty), (2, None, "user", ""), (2, 1, "user", nasty), (None, 1, "assistant", nasty)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("example", F.lit(1))
    ex = chat.chat_examples(df)
    assert ex.where("conv_id = 1").count() == 3 and ex.where("conv_id = 2").count() == 1
    got = {r.conv_id: r for r in chat.chat_digest(ex).collect()}
    turns = [(r or "", t or "") for _, _, r, t in rows[:5]]
    assert got[1].turns_sha256 == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest()
    loss = "".join(t for r, t in turns if r == "assistant")
    assert (got[1].loss_chars, got[1].loss_sha256) == (len(loss), hashlib.sha256(loss.encode()).hexdigest())
    assert got[1].n_turns == 5 and got[2].n_turns == 2 and got[2].loss_chars == 0 and got[None].loss_chars == len(nasty)
    assert chat.chat_examples(df.limit(0)).count() == 0
