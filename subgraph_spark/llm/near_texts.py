"""Near copies of texts by SimHash: those whose word shingles have a Jaccard similarity of ``least`` or more.

Fingerprints are those of ``simhash``, over the distinct shingles of ``width`` words, and hang in its Burkhard-Keller trees, with a
radius that the similarity asks for: two sets at 0.8 are 10 bits apart on average, and more than 24 with probability 1e-5 or
less. Blocks of bits would hardly part texts at this radius, so shards are made by min-wise keys: the smallest values of 192
multiplied hashes make 32 keys of six each. A pair at 0.8 shares none with probability 6e-5, a closer one with less. Shards of
the same texts are searched once; a large shard is cut into trees of about SHARD texts, which then are one group of candidates.

Confirmation. Links within the radius only group candidates; what counts is the exact similarity. In rounds, every text
of a group is compared with the group's first, by the shingles that both have: those alike are linked and done. By the triangle
inequality of the Jaccard distance, only texts within twice the distance of the first can be near copies of those linked to it,
and are compared with them; what isn't linked goes on to the next round, with a first of its own. So a large group
of copies takes one comparison a text. What is left after some rounds, and the texts at the border, meet through
an inverted index, in parts of a bounded number of shingles; what leaves a part is a forest of links.

Defined cases: a null text is empty; texts without words are alike; rows are told apart by their place, so null and repeated
ids are rows of their own; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import in_arrow, stage, whole_text
from .components import components
from .exact_dedup import located
from .simhash import SHARD, BKTree, forest, majority, shingle_hashes

#: Bits by which fingerprints of near copies may differ.
RADIUS = 24
#: Keys of a text, and minima in each.
KEYS, MINIMA = 32, 6
#: Shingles of a part that is indexed, about; queries come in slices of twice that.
PART = 1 << 21
#: Rounds in which a group's texts are compared with its first.
ROUNDS = 4
_FACTORS = np.random.default_rng(5).integers(0, 1 << 32, KEYS * MINIMA, dtype=np.uint32) | np.uint32(1)
#: Hashes that are multiplied at a time.
_BLOCK = 4096
#: Hash values that tell candidates from other rows.
_MARKS = 1 << 20


def shingles(text: str, width: int = 5) -> np.ndarray:
    """The sorted distinct hashes of a text's shingles; a text of fewer words is one shingle."""
    return np.unique(np.concatenate(list(shingle_hashes(text.encode().lower().split(), width))))


def keys_of(hashes: np.ndarray) -> list[int]:
    """The keys of a shingle set, as signed longs."""
    from xxhash import xxh64_digest

    high = (hashes >> np.uint64(32)).astype(np.uint32)
    least = np.full(len(_FACTORS), 0xFFFFFFFF, np.uint32)
    for at in range(0, len(high), _BLOCK):
        np.minimum(least, (_FACTORS[:, None] * high[None, at : at + _BLOCK]).min(axis=1), out=least)
    return [int.from_bytes(xxh64_digest(x.tobytes(), k), "big", signed=True) for k, x in enumerate(least.reshape(KEYS, MINIMA))]


def confirmed(sets: list[np.ndarray], hangs: np.ndarray, asks: np.ndarray, least: tuple[int, int]) -> list[tuple[int, int]]:
    """Index pairs that join the same sets as all pairs of an asking and a hanging set with similarity ``least`` or more."""
    index = np.flatnonzero(hangs)
    lengths = np.array([len(sets[x]) for x in index], np.int64)
    flat = np.concatenate([sets[x] for x in index]) if len(index) else np.zeros(0, np.int64)
    order = np.argsort(flat, kind="stable")
    flat, owner = flat[order], np.repeat(np.arange(len(index)), lengths)[order]
    root, links, classes = list(range(len(sets))), [], len(sets)

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    for q in np.flatnonzero(asks).tolist():
        if classes == 1:
            break
        low, high = np.searchsorted(flat, sets[q]), np.searchsorted(flat, sets[q], "right")
        count = high - low
        place = np.repeat(low - (np.cumsum(count) - count), count) + np.arange(count.sum())
        common = np.bincount(owner[place], minlength=len(index))
        for x in index[common * least[1] >= least[0] * (len(sets[q]) + lengths - common)].tolist():
            a, b = find(q), find(x)
            if a != b:
                root[max(a, b)] = min(a, b)
                links.append((q, x))
                classes -= 1
    return links


def _groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[list[tuple]]:
    """Rows that share the first ``keys`` columns, which come sorted; lists as arrays."""
    held: list[tuple] = []
    for batch in batches:
        columns = [[x.values.to_numpy() for x in c] if pa.types.is_list(c.type) else c.to_pylist() for c in batch.columns]
        for row in zip(*columns, strict=True):
            if held and row[:keys] != held[-1][:keys]:
                yield held
                held = []
            held.append(row)
    if held:
        yield held


def candidates(marked: DataFrame, radius: int = RADIUS, shard: int = SHARD) -> DataFrame:
    """Rows (node, root) of the texts that share a shard with one whose fingerprint is near; from (node, fp, keys)."""
    places = marked.select("node", "fp", F.explode("keys").alias("key"))
    shared = places.groupBy("key").agg(F.count("*").alias("n"), F.min("node").alias("first"), F.max("node").alias("last"), F.bit_xor(F.xxhash64("node")).alias("mix")).filter("n > 1")
    shared = shared.dropDuplicates(["n", "first", "last", "mix"]).select("key", "n", "first")
    rows = places.join(shared, "key").select("key", F.pmod(F.xxhash64("node"), F.ceil(F.col("n") / shard)).alias("tree"), (F.col("n") > shard).alias("cut"), "first", "node", "fp")
    rows = rows.repartition("key", "tree").sortWithinPartitions("key", "tree", "fp", "node")

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in _groups(batches, 2):
            _, _, cut, first, node, fp = zip(*group, strict=True)
            node, fp = np.array(node, np.int64), np.array(fp, np.int64).view(np.uint64)
            if cut[0]:  # a part of a large shard
                a, b = node, np.full(len(node), first[0])
            else:
                values, at, of = np.unique(fp, return_index=True, return_inverse=True)
                one, other = forest(values, BKTree(values), radius)
                a = np.concatenate([node, node[at[np.searchsorted(values, one)]]])
                b = np.concatenate([node[at[of]], node[at[np.searchsorted(values, other)]]])
            a, b = a[a != b], b[a != b]
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    return components(rows.mapInArrow(search, "a long, b long"))


def _compared(work: DataFrame, leaders: DataFrame, sets: DataFrame, least: tuple[int, int]) -> DataFrame:
    """Rows (root, node, leader, kind): kind 0 is a near copy of the leader, 1 may be one of such, 2 can't."""
    other = sets.select(F.col("node").alias("leader"), F.col("shingles").alias("theirs"))
    rows = work.join(leaders, "root").filter("node <> leader").join(sets, "node").join(other, "leader")
    common = F.size(F.array_intersect("shingles", "theirs"))
    rows = rows.select("root", "node", "leader", common.alias("common"), (F.size("shingles") + F.size("theirs") - common).alias("all"))
    alike = F.col("common") * least[1] >= F.col("all") * least[0]
    border = F.col("common") * least[1] >= F.col("all") * (2 * least[0] - least[1])
    return rows.select("root", "node", "leader", F.when(alike, 0).when(border, 1).otherwise(2).alias("kind"))


def _indexed(meet: DataFrame, sets: DataFrame, least: tuple[int, int], part: int) -> DataFrame:
    """Links (a, b) among rows (place, node, hangs, asks): between those that ask and those that hang in a place."""
    rows = meet.join(sets.withColumn("m", F.size("shingles")), "node")
    sizes = rows.groupBy("place").agg(F.ceil(F.sum("m") / part).cast("int").alias("trees"), F.ceil(F.sum("m") / (2 * part)).cast("int").alias("slices"))
    rows = rows.join(sizes, "place")
    # What hangs does so in one part of its place, which goes to all slices of queries; what asks does so in every part, in one slice.
    rows = rows.select("*", F.pmod(F.xxhash64("node"), F.col("trees")).alias("own"), F.pmod(F.hash("node"), F.col("slices")).alias("mine"))
    trees = F.when(F.col("asks"), F.sequence(F.lit(0), F.col("trees") - 1)).otherwise(F.array(F.col("own").cast("int")))
    rows = rows.select("*", F.explode(trees).alias("tree"))
    here = F.col("hangs") & (F.col("own") == F.col("tree"))
    rows = rows.select("*", F.explode(F.when(here, F.sequence(F.lit(0), F.col("slices") - 1)).otherwise(F.array(F.col("mine").cast("int")))).alias("slice"))
    rows = rows.select("place", "tree", "slice", "node", "shingles", here.alias("hangs"), (F.col("asks") & (F.col("mine") == F.col("slice"))).alias("asks"))
    rows = rows.repartition("place", "tree", "slice").sortWithinPartitions("place", "tree", "slice", "node")

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for group in _groups(batches, 3):
            _, _, _, node, found, hangs, asks = zip(*group, strict=True)
            pairs = confirmed(list(found), np.array(hangs), np.array(asks), least)
            if pairs:
                yield pa.RecordBatch.from_arrays([pa.array([node[x[k]] for x in pairs], pa.int64()) for k in (0, 1)], names=["a", "b"])

    return rows.mapInArrow(search, "a long, b long")


def classes(groups: DataFrame, sets: DataFrame, least: tuple[int, int], part: int = PART, rounds: int = ROUNDS) -> DataFrame:
    """Rows (node, root) of the nodes that links reach, from written candidates (node, root) and sets (node, shingles)."""
    work, linked, meet = groups.select("root", "node"), [], []
    for _ in range(rounds):
        leaders = work.groupBy("root").agg(F.min("node").alias("leader"), F.count("*").alias("n")).filter("n > 1").drop("n")
        met = stage(_compared(work, leaders, sets, least), "compared")
        if met.isEmpty():
            break
        near = met.filter("kind = 0").select("node", "leader")
        linked.append(near)
        border = met.filter("kind = 1").select(F.col("leader").alias("place"), "node")
        hung = near.join(border.select(F.col("place").alias("leader")).distinct(), "leader", "left_semi").select(F.col("leader").alias("place"), "node")
        meet += [border.select("place", "node", F.lit(False).alias("hangs"), F.lit(True).alias("asks")), hung.select("place", "node", F.lit(True).alias("hangs"), F.lit(False).alias("asks"))]
        work = met.filter("kind > 0").select("root", "node")
    else:
        many = work.groupBy("root").count().filter("count > 1").select("root")
        # Leaders are the first nodes of their places; no place of a round is -1 - root.
        meet.append(work.join(many, "root", "left_semi").select((-1 - F.col("root")).alias("place"), "node", F.lit(True).alias("hangs"), F.lit(True).alias("asks")))
    if not meet:
        return groups.limit(0)
    none = groups.limit(0).select("node", F.col("root").alias("leader"))
    near = stage(reduce(DataFrame.unionByName, linked, none), "near")
    links = stage(_indexed(stage(reduce(DataFrame.unionByName, meet), "meet"), sets, least, part), "links")
    own = near.select("node", F.col("leader").alias("root")).unionByName(near.select(F.col("leader").alias("node"), F.col("leader").alias("root")).distinct())
    if links.isEmpty():
        return own
    # Links between classes: a node that is in none is its own.
    class_of = lambda rows, end: rows.join(own.select(F.col("node").alias(end), F.col("root").alias(f"{end}_root")), end, "left").withColumn(end, F.coalesce(f"{end}_root", end)).drop(f"{end}_root")
    joined = components(class_of(class_of(links, "a"), "b").select("a", "b"))
    every = own.unionByName(joined.join(own, "node", "left_anti").select("node", F.col("node").alias("root")))
    upper = joined.select(F.col("node").alias("root"), F.col("root").alias("upper"))
    return every.join(upper, "root", "left").select("node", F.coalesce("upper", "root").alias("root"))


def near_copies(docs: DataFrame, width: int = 5, least: tuple[int, int] = (4, 5), id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS, shard: int = SHARD, part: int = PART, rounds: int = ROUNDS) -> DataFrame:
    """Rows (doc_id, file, row, root) of the documents that have a near copy; root is the same for all that links reach."""

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingles(x.as_py(), width) for x in batch.column(3)]
            fps = np.array([majority([x]) for x in sets], np.uint64)
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(fps.view(np.int64)), pa.array([keys_of(x) for x in sets], pa.list_(pa.int64()))], names=["doc_id", "file", "row", "fp", "keys"])

    rows = located(docs).select(F.col(id_col).cast("long").alias("doc_id"), F.col("__own_file").alias("file"), F.col("__own_row").alias("row"), whole_text(text_col).alias("text"))
    marked = in_arrow(rows, mark, "doc_id long, file string, row long, fp long, keys array<long>")
    # Written once, so that a row keeps its number.
    marked = stage(marked.withColumn("node", F.monotonically_increasing_id()), "sketches")
    groups = stage(candidates(marked, radius, shard), "groups")

    hits = stage(groups.join(marked.drop("keys", "fp"), "node"), "candidates")
    marker = F.pmod(F.xxhash64("file", "row"), F.lit(_MARKS))
    marks = F.broadcast(hits.select(marker.alias("mark")).distinct())
    texts = rows.drop("doc_id").withColumn("mark", marker).join(marks, "mark", "left_semi").drop("mark").join(hits.select("node", "file", "row"), ["file", "row"])

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sets = [shingles(x.as_py(), width).view(np.int64) for x in batch.column(1)]
            ends = np.append(0, np.cumsum([len(x) for x in sets]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate(sets)))], names=["node", "shingles"])

    sets = stage(in_arrow(texts.select("node", "text"), gather, "node long, shingles array<long>"), "shingle-sets")
    linked = classes(groups, sets, least, part, rounds)
    return linked.join(hits.select("node", "doc_id", "file", "row"), "node").select("doc_id", "file", "row", "root")
