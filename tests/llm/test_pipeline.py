"""The stages of corpus_pipeline, each against a brute-force version over its own input."""

import re

import corpus_pipeline as C
from test_dedup import roots, squeeze
from test_near_texts import alike, slow_shingles
from test_tokens_and_packing import check_packed, pieces_of

from subgraph_spark.llm import quality
from subgraph_spark.llm.common import stage, table


def rows_of(df):
    return sorted(map(tuple, df.collect()), key=repr)


def test_stages(spark, sf):
    docs = stage(table(spark, sf, "documents"), "docs")
    columns = docs.columns
    names = [n for n, _ in C.STAGES]
    assert names == ["quality classifier", "exact dedup", "simhash near-dedup", "mixing", "best-fit packing"]
    step = dict(C.STAGES)

    good = stage(step[names[0]](spark, docs, sf), "good")
    scores = {r.doc_id: r.score for r in quality.quality_scores(docs, table(spark, sf, "labels")).select("doc_id", "score").collect()}
    assert good.columns == columns
    assert rows_of(good) == sorted((tuple(r) for r in docs.collect() if scores[r.doc_id] >= 0.3), key=repr)

    exact = stage(step[names[1]](spark, good, sf), "exact")
    first = {}
    for r in sorted(good.collect(), key=lambda r: r.doc_id):
        first.setdefault(squeeze(r.text), tuple(r))
    assert exact.columns == columns and rows_of(exact) == sorted(first.values(), key=repr)

    near = stage(step[names[2]](spark, exact, sf), "near")
    rows = sorted(exact.collect(), key=lambda r: r.doc_id)
    sets = [slow_shingles(r.text) for r in rows]
    root = roots(len(rows), [(i, j) for i in range(len(rows)) for j in range(i) if alike(sets[i], sets[j])])
    assert near.columns == columns and rows_of(near) == sorted((tuple(r) for i, r in enumerate(rows) if root[i] == i), key=repr)

    mix = stage(step[names[3]](spark, near, sf), "mix")
    have = {tuple(r) for r in near.collect()}
    count = {}
    for r in mix.collect():
        count[tuple(r)] = count.get(tuple(r), 0) + 1
    assert mix.columns == columns and set(count) <= have and max(count.values()) <= 2
    size = lambda r: len(re.findall(r"[^\x20\x09-\x0D]+", r[1]))
    assert abs(sum(n * size(r) for r, n in count.items()) - 1.5 * sum(map(size, have))) < 0.01 * sum(map(size, have))

    packed = step[names[4]](spark, mix, sf).collect()
    check_packed(packed, list(pieces_of([(r.doc_id, r.text) for r in mix.collect()], 2048)), 2048)


def test_awkward_documents(spark, docs, tmp_path, sf):
    import shutil

    shutil.copy(f"{sf}/labels.parquet", tmp_path / "labels.parquet")
    shutil.copytree(docs.inputFiles()[0].removeprefix("file://").rsplit("/", 1)[0], tmp_path / "documents.parquet")
    out = C.run(spark, str(tmp_path))
    assert out.count() > 100
    # Extra columns go through all stages but the last.
    kept = docs
    for name, f in C.STAGES[:-1]:
        kept = stage(f(spark, kept, str(tmp_path)), "kept")
        assert kept.columns == docs.columns
    empty = stage(docs.limit(0), "none")
    for name, f in C.STAGES:
        assert f(spark, empty, str(tmp_path)).count() == 0


def test_run(spark, sf):
    assert C.run(spark, sf).count() > 0
