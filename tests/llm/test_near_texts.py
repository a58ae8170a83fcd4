"""Near copies by shingles, against brute force."""

import random
import re

import corpus_pipeline as C
import numpy as np
from test_dedup import roots

from subgraph_spark.llm import near_texts
from subgraph_spark.llm.common import stage


def slow_shingles(text, width=5):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(words[i : i + width]) for i in range(max(1, len(words) - width + 1))}


def alike(a, b):
    return 5 * len(a & b) >= 4 * len(a | b)


def planted():
    """Texts, copies of them with a few words changed, and texts that share a long passage only."""
    rng = random.Random(3)
    words = [f"w{i}" for i in range(3000)]
    passage = rng.choices(words, k=40)
    texts = []
    for n in (3, 12, 60, 60, 200, 200, 600):
        base = passage + rng.choices(words, k=n)
        texts.append(base)
        for changes in (1, 1, 2, 3, 4):
            copy = list(base)
            for _ in range(changes):
                copy[rng.randrange(len(copy))] = rng.choice(words)
            texts.append(copy)
    return [" ".join(x) for x in texts] + [None, "", "One two", "one  TWO", "one two three"]


def test_near_copies(spark):
    texts = planted()
    sets = [slow_shingles(x) for x in texts]
    links = [(i, j) for i in range(len(sets)) for j in range(i) if alike(sets[i], sets[j])]
    root = roots(len(sets), links)
    expected = {frozenset(i for i, r in enumerate(root) if r == x) for x in set(root)}
    docs = stage(spark.createDataFrame([(i, x) for i, x in enumerate(texts)], "doc_id long, text string").repartition(3), "docs")
    for how in ({}, {"part": 300, "rounds": 0}, {"part": 300, "rounds": 1, "shard": 4}):
        groups = {}
        for r in near_texts.near_copies(docs, **how).collect():
            groups.setdefault(r.root, set()).add(r.doc_id)
        assert {frozenset(x) for x in groups.values()} == {x for x in expected if len(x) > 1}
    assert near_texts.near_copies(docs.limit(0)).count() == 0
    stays = sorted(r.doc_id for r in C.near(spark, docs, None).collect())
    assert stays == sorted(min(x) for x in expected)


def test_keys_miss_few_pairs_at_the_bound():
    rng = np.random.default_rng(1)
    missed = 0
    for n in [9] * 300 + [90] * 300 + [900] * 100:
        # 8 of 10 in common
        every = rng.integers(0, 1 << 64, n // 9 * 10, dtype=np.uint64)
        a, b = every[: n // 9 * 9], np.concatenate([every[: n // 9 * 8], every[n // 9 * 9 :]])
        missed += not set(near_texts.keys_of(np.unique(a))) & set(near_texts.keys_of(np.unique(b)))
    assert missed <= 1


def test_near_stage_keeps_one_row_a_group_whatever_the_ids(spark):
    base = [" ".join(f"{x}{i}" for i in range(50)) for x in "abcd"]
    rows = [(1, base[0]), (None, base[0] + " more"), (None, base[1]), (None, base[2]), (None, base[2] + " more"), (7, base[3]), (7, base[3] + " more"), (7, "quite another text of the same id")]
    docs = stage(spark.createDataFrame(rows, "doc_id long, text string").coalesce(1), "docs")
    got = [tuple(r) for r in C.near(spark, docs, None).collect()]
    assert C.near(spark, docs, None).columns == docs.columns
    assert sorted(got, key=repr) == sorted([rows[0], rows[2], rows[3], rows[5], rows[7]], key=repr)
