"""Exact and near duplicates, of texts and of vectors, against brute force."""

import hashlib
import re

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from subgraph_spark.llm import exact_dedup, near_vectors, simhash
from subgraph_spark.llm.components import components


def roots(n, links):
    parent = list(range(n))

    def find(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in links:
        p, q = find(a), find(b)
        parent[max(p, q)] = min(p, q)
    return [find(x) for x in range(n)]


def squeeze(text):
    return re.sub(r"[\x20\x09-\x0D]+", " ", text or "")


def test_exact(docs, docs_rows, empty):
    got = exact_dedup.duplicate_groups(docs).collect()
    groups = {}
    for d, t, *_ in docs_rows:
        groups.setdefault(squeeze(t), []).append(d)
    keep = {k: min((x for x in v if x is not None), default=None) for k, v in groups.items()}
    expected = sorted(((d, keep[squeeze(t)], len(groups[squeeze(t)]), hashlib.sha256(squeeze(t).encode()).hexdigest()) for d, t, *_ in docs_rows), key=repr)
    assert sorted(((r.doc_id, r.keep_id, r.group_size, r.sha256) for r in got), key=repr) == expected
    assert sum(r.kept for r in got) == len(groups)  # one row a group, also where rows share the smallest id
    assert all(r.doc_id == r.keep_id for r in got if r.kept)
    assert exact_dedup.duplicate_groups(empty).count() == 0


def test_digests_that_collide_are_told_apart_by_their_bytes(docs, docs_rows):
    weak = lambda text: F.unhex(F.substring(F.sha2(text, 256), 1, 2))
    strong = exact_dedup.duplicate_groups(docs).select("doc_id", "keep_id", "group_size", "kept", "sha256")
    got = exact_dedup.duplicate_groups(docs, digest=weak).select("doc_id", "keep_id", "group_size", "kept", "sha256")
    assert sorted(map(tuple, got.collect()), key=repr) == sorted(map(tuple, strong.collect()), key=repr)


def test_rows_that_lie_in_no_file(spark):
    df = spark.createDataFrame([(2, "a b"), (1, "a  b"), (3, "c")], "doc_id long, text string").filter("doc_id > 0")
    got = {r.doc_id: (r.keep_id, r.kept) for r in exact_dedup.duplicate_groups(df).collect()}
    assert got == {2: (1, False), 1: (1, True), 3: (3, True)}


def slow_fingerprint(text, width=3):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return 0
    hashes = [xxhash.xxh64_intdigest(" ".join(words[i : i + width]).encode(), seed=42) for i in range(max(1, len(words) - width + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_fingerprints(docs_rows, monkeypatch):
    monkeypatch.setattr(simhash, "_BLOCK", 7)
    for _, t, *_ in docs_rows[:40] + docs_rows[-11:-8] + docs_rows[-7:]:
        assert simhash.fingerprint(t or "") == slow_fingerprint(t)


@pytest.mark.parametrize("radius", [0, 2, 5])
def test_tree_finds_all_within_the_radius(radius):
    rng = np.random.default_rng(3)
    centre = rng.integers(0, 1 << 63, 20, dtype=np.uint64)
    values = np.unique(np.concatenate([centre, *[centre ^ np.uint64(1 << int(a) | 1 << int(b)) for a, b in rng.integers(0, 63, (30, 2))]]))
    queries = np.concatenate([values[::3], rng.integers(0, 1 << 63, 50, dtype=np.uint64)])
    got = {(int(q), int(v)) for a, b in simhash.BKTree(values).links(queries, radius) for q, v in zip(queries[a], values[b], strict=True)}
    assert got == {(int(q), int(v)) for q in queries for v in values if int(q ^ v).bit_count() <= radius}


@pytest.mark.parametrize("shard", [3, 4096])
def test_links_of_fingerprints(spark, shard):
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 64, 12, dtype=np.uint64)
    near = [base]
    for _ in range(25):
        near.append(base ^ (np.uint64(1) << rng.integers(0, 64, 12, dtype=np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 12, dtype=np.uint64)))
    values = np.unique(np.concatenate([*near, base[0] ^ np.arange(64, dtype=np.uint64)]))
    table = spark.createDataFrame([(int(x),) for x in values.view(np.int64)], "fp long")
    got = {r.node: r.root for r in components(simhash.link_fingerprints(table, 2, shard)).collect()}
    links = [(i, j) for i in range(len(values)) for j in range(i) if int(values[i] ^ values[j]).bit_count() <= 2]
    root = roots(len(values), links)
    signed = values.view(np.int64).tolist()
    same = lambda label: {frozenset(v for v, x in zip(signed, label, strict=True) if x == r) for r in set(label)}
    assert same([got.get(v, v) for v in signed]) == same(root)


def test_near_duplicates(docs, docs_rows, empty):
    marks = [slow_fingerprint(t) for _, t, *_ in docs_rows]
    links = [(i, j) for i in range(len(marks)) for j in range(i) if (marks[i] ^ marks[j]).bit_count() <= 2]
    root = roots(len(marks), links)
    least = {r: min((docs_rows[i][0] for i in range(len(marks)) if root[i] == r and docs_rows[i][0] is not None), default=None) for r in set(root)}
    expected = sorted(((d[0], f"{m:016x}", least[r]) for d, m, r in zip(docs_rows, marks, root, strict=True)), key=repr)
    assert sorted(map(tuple, simhash.near_duplicates(docs).collect()), key=repr) == expected
    assert simhash.near_duplicates(empty).count() == 0


def test_components(spark):
    chain = [(i, i + 1) for i in range(40)] + [(100, 101), (101, 100), (7, 7), (-5, 60), (60, 61)] + [(200, 200 + i) for i in range(1, 50)]
    got = {r.node: r.root for r in components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert {got[i] for i in range(41)} == {0} and got[101] == got[100] == 100 and got[61] == -5 and {got[200 + i] for i in range(50)} == {200}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def vector_rows():
    rng = np.random.default_rng(11)
    base = rng.standard_normal((30, 16))
    rows = [x for x in base] + [x * 3 for x in base[:5]] + [x for x in base[:5]]
    rows += [base[0] + rng.standard_normal(16) * s for s in np.linspace(0.01, 0.5, 60)]
    out = [(i, [float(v) for v in x]) for i, x in enumerate(rows)]
    out += [(900, None), (901, [0.0] * 16), (902, [float("nan")] * 16), (903, [None] + [1.0] * 15), (904, [float("inf")] * 16), (905, []), (906, [1.0, 2.0]), (907, [2.0, 4.0]), (None, [float(v) for v in base[9]])]
    return out


@pytest.mark.parametrize("block", [8, 2048])
def test_vectors(spark, block, monkeypatch):
    monkeypatch.setattr(near_vectors, "BLOCK", block)
    rows = vector_rows()

    def unit(x):
        if not x or any(v is None or not np.isfinite(v) for v in x) or not any(x):
            return None
        return np.array(x) / np.linalg.norm(x)

    units = [unit(x) for _, x in rows]
    links = [(i, j) for i in range(len(rows)) for j in range(len(rows)) if i != j and units[i] is not None and units[j] is not None and len(units[i]) == len(units[j]) and units[i] @ units[j] >= 0.95]
    root = roots(len(rows), links)
    least = {r: min((rows[i][0] for i in range(len(rows)) if root[i] == r and rows[i][0] is not None), default=None) for r in set(root)}
    degree = [0] * len(rows)
    for a, _ in links:
        degree[a] += 1
    expected = sorted(((rows[i][0], degree[i], least[root[i]], rows[i][0] == least[root[i]]) for i in range(len(rows))), key=repr)
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>" if False else "vec_id long, embedding array<double>").withColumn("v", F.lit("clash")).withColumn("node", F.lit(1))
    got = near_vectors.near_duplicate_vectors(df, 0.95, miss=1e-9)
    assert sorted(map(tuple, got.collect()), key=repr) == expected


def test_no_vectors(spark):
    assert near_vectors.near_duplicate_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_tables_follow_the_number_of_nodes():
    for n in (10, 10_000, 10**9):
        bits, tables = near_vectors.plan_tables(n, 0.95, 1e-4)
        meet = (1 - np.arccos(0.95) / np.pi) ** bits
        assert (1 - meet) ** tables <= 1e-4 < (1 - meet) ** (tables - 1)


def test_planted_pairs_at_the_threshold_are_found_by_default(spark):
    """The registered setting on 1,500 pairs whose cosine is barely 0.95 or a little below: at most one link is missed, and none is made up."""
    rng = np.random.default_rng(12)
    n, dim = 1500, 64
    a = rng.standard_normal((n, dim))
    a /= np.linalg.norm(a, axis=1, keepdims=True)
    b = rng.standard_normal((n, dim))
    b -= (a * b).sum(1, keepdims=True) * a
    b /= np.linalg.norm(b, axis=1, keepdims=True)
    cosine = np.where(np.arange(n) % 5 == 0, 0.9499, rng.uniform(0.95001, 0.951, n))[:, None]
    every = np.concatenate([a, cosine * a + np.sqrt(1 - cosine**2) * b])
    df = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(every)], "vec_id long, embedding array<double>")
    unit = every / np.linalg.norm(every, axis=1, keepdims=True)
    expected = (unit @ unit.T >= 0.95).sum(1) - 1
    got = {r.vec_id: r.n_links for r in near_vectors.near_duplicate_vectors(df).collect()}
    assert expected.sum() == 2 * n * 4 // 5
    missed = sum(int(expected[i]) - got[i] for i in got)
    assert 0 <= missed <= 2 and all(got[i] <= expected[i] for i in got)


def test_shards_of_two_are_as_trees():
    """The short way for two fingerprints gives what trees give, whichever hangs or asks."""
    rng = np.random.default_rng(8)
    for _ in range(400):
        a = int(rng.integers(0, 1 << 63))
        b = a
        for bit in rng.choice(64, rng.integers(1, 6), replace=False):
            b ^= 1 << int(bit)
        fps = np.array(sorted((a, b)), np.uint64)
        for hangs, asks in (((1, 1), (1, 1)), ((1, 0), (0, 1)), ((0, 1), (1, 0)), ((1, 0), (1, 1)), ((1, 1), (0, 1)), ((1, 0), (1, 0))):
            hangs, asks = np.array(hangs, bool), np.array(asks, bool)
            one, other = simhash.pair(fps, hangs, asks, 2), simhash.forest(fps[asks], simhash.BKTree(fps[hangs]), 2)
            assert [x.tolist() for x in one] == [x.tolist() for x in other]


def test_the_stream_goes_on_with_its_state(spark, tmp_path):
    """Rows that come after the first run join the groups that its state has."""
    schema = "digest binary, doc_id long, file string, row long"
    rows = lambda ids: spark.createDataFrame([(bytes([i % 3]), i, "f", i) for i in ids], schema)
    folder, state = str(tmp_path / "rows"), str(tmp_path / "state")
    for ids, expected in ((range(5, 9), {0: (6, 1), 1: (7, 1), 2: (5, 2)}), (range(0, 5), {0: (0, 3), 1: (1, 3), 2: (2, 3)}), ((), {0: (0, 3), 1: (1, 3), 2: (2, 3)})):
        if ids:
            rows(ids).write.mode("append").parquet(folder)
        got = exact_dedup.keyed_state(folder, spark.read.parquet(folder), folder=state).collect()
        assert {r.digest[0]: (r["first"].doc_id, r.n) for r in got} == expected
