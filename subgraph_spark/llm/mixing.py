"""Mixing sources to target weights by entropy balancing, in DataFrame operations alone.

Wanted are rates of documents (how often each is taken, ``cap`` times at most) that meet every source's target of
words and depart least from one common rate, in the sense of relative entropy. The dual of this convex problem has one
multiplier per source; its solution tilts the rate exponentially. Newton's steps, each kept inside a shrinking bracket,
take the gradients and curvatures from sums over all documents. A rate depends on the source and size
alone, so the sums run over a table of sizes' counts, which is complete and small.

Every document counts the same (``entropy="documents"``), so the tilt goes with the size: rate = share * exp(multiplier * size /
mean size), up to the cap. With ``"words"`` every word does; the tilt then is one for a source's documents, which share one rate.

Rounding. Every document is taken as often as its rate's whole part. The words that a source still lacks come from documents in
the order of hash / remaining part, a draw in which a document's chance goes with its remaining part. A document that would pass
what is missing is skipped, and the draw goes on down the order until no document that is left fits. A pass cumulates over buckets of
the order first, and over rows only in the bucket where the sum is reached: it ends at a document larger than what then is missing. As
only documents of that size or less go on, every pass leaves less, and the passes that a source has seen decide on each
of its documents. A few documents whose sizes come closest to what then is missing settle the rest. Documents are told apart by a hash
of what they hold, and equal ones by their place.

Defined cases: a null text has size 0, and is taken 0 words; a null source is one source, last in order; null and repeated ids
are kept, one row per row; an empty table gives no rows; other columns are ignored. Sources of no words have target 0.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import drop, stage, whole_text
from .exact_dedup import located

WORD = r"[^\x20\x09-\x0D]+"
#: Buckets for a unit of the drawing order.
_BUCKETS = 4096


def word_count(text_col: str = "text") -> Column:
    return F.regexp_count(whole_text(text_col), F.lit(WORD)).cast("long")


def line_of(id_col: str = "doc_id", text_col: str = "text") -> Column:
    """What tells documents apart in the draw, wherever they lie."""
    return F.xxhash64(F.col(id_col).cast("long"), whole_text(text_col))


def sizes_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """Written rows (doc_id, source, size, line, file, row); line is a hash of the document, file and row are its place."""
    rows = located(docs).select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), word_count(text_col).alias("size"), line_of(id_col, text_col).alias("line"), F.col("__own_file").alias("file"), F.col("__own_row").alias("row"))
    return stage(rows, "sizes")


def targets(source_sizes: DataFrame, share: float, cap: float, weights: tuple[int, ...]) -> DataFrame:
    """From (source, source_size) to (source, source_size, target): shares by weight, stopped at ``cap`` times the size, the excess shared again.

    Sources fill up in the order of room per weight, so one pass finds the level at which the others stand. The windows are over the
    sources, a row each.
    """
    named = Window.orderBy(F.asc_nulls_last("source"))
    weight = F.element_at(F.array(*map(F.lit, weights)), F.pmod(F.row_number().over(named) - 1, F.lit(len(weights))) + 1)
    rows = source_sizes.withColumn("weight", weight.cast("double")).withColumn("room", F.col("source_size") * F.lit(float(cap)))
    everything = Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing).orderBy(F.asc_nulls_last("source"))
    rows = rows.withColumn("words", F.lit(float(share)) * F.sum("source_size").over(everything)).withColumn("weights", F.sum("weight").over(everything))
    filling = Window.orderBy(F.col("room") / F.col("weight"), F.asc_nulls_last("source"))
    before = filling.rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.withColumn("level", (F.col("words") - F.coalesce(F.sum("room").over(before), F.lit(0.0))) / (F.col("weights") - F.coalesce(F.sum("weight").over(before), F.lit(0.0))))
    # Once a source has room left, so have all after it.
    rows = rows.withColumn("full", F.min(F.col("room") <= F.col("level") * F.col("weight")).over(filling.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    level = F.first(F.when(~F.col("full"), F.col("level")), ignorenulls=True).over(filling.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return rows.withColumn("level", level).select("source", "source_size", F.when(F.col("full"), F.col("room")).otherwise(F.col("level") * F.col("weight")).alias("target"))


def _tilt(entropy: str, size: Column, mean: Column) -> Column:
    return F.lit(1.0) if entropy == "words" else size / mean


def balance(counts: DataFrame, wanted: DataFrame, rate: float, cap: float, entropy: str, near: float = 1e-9, steps: int = 60) -> DataFrame:
    """Multipliers: (source, source_size, target, mean, lam) from written counts (source, size, n) and (source, source_size, target)."""
    means = counts.filter("size > 0").groupBy("source").agg((F.sum(F.col("n") * F.col("size")) / F.sum("n")).alias("mean"))
    now = wanted.join(means, wanted["source"].eqNullSafe(means["source"]), "left").select(wanted["*"], "mean")
    now = stage(now.select("*", F.lit(0.0).alias("lam"), F.lit(-700.0).alias("low"), F.lit(700.0).alias("high"), F.lit(1.0).alias("off")), "multipliers")
    for _ in range(steps):
        if now.filter(F.col("off") > near).isEmpty():
            return now
        both = counts.withColumnRenamed("source", "of").join(now, F.col("of").eqNullSafe(F.col("source")))
        tilt = _tilt(entropy, F.col("size"), F.col("mean"))
        raw = F.lit(rate) * F.exp(F.least(F.col("lam") * tilt, F.lit(700.0)))
        words = F.col("n") * F.col("size") * F.least(raw, F.lit(float(cap)))
        sums = both.groupBy("of").agg(F.sum(words).alias("made"), F.sum(F.when(raw < cap, words * tilt).otherwise(0.0)).alias("slope"))
        met = now.join(sums, F.col("of").eqNullSafe(F.col("source"))).withColumn("over", F.col("made") - F.col("target"))
        met = met.withColumn("low", F.when(F.col("over") < 0, F.greatest("low", "lam")).otherwise(F.col("low"))).withColumn("high", F.when(F.col("over") > 0, F.least("high", "lam")).otherwise(F.col("high")))
        newton = F.col("lam") - F.col("over") / F.nullif(F.col("slope"), F.lit(0.0))
        inside = (newton > F.col("low")) & (newton < F.col("high"))
        # Where every document is at the cap or none is wanted, there is nothing to solve.
        off = F.when((F.col("target") <= 0) | (F.col("target") >= cap * F.col("source_size")), F.lit(0.0)).otherwise(F.abs("over") / F.col("target"))
        step = F.when(off <= near, F.col("lam")).when(inside, newton).otherwise((F.greatest("low", F.col("lam") - 20) + F.least("high", F.col("lam") + 20)) / 2)
        before, now = now, stage(met.select("source", "source_size", "target", "mean", step.alias("lam"), "low", "high", off.alias("off")), "multipliers")
        drop(before)
    return now


def rate_of(entropy: str, rate: float, cap: float) -> Column:
    """A document's rate, from size, source_size, target, mean and lam."""
    tilted = F.lit(rate) * F.exp(F.least(F.col("lam") * _tilt(entropy, F.col("size"), F.col("mean")), F.lit(700.0)))
    return F.when((F.col("target") <= 0) | (F.col("size") <= 0), F.lit(0.0)).when(F.col("target") >= cap * F.col("source_size"), F.lit(float(cap))).otherwise(F.least(tilted, F.lit(float(cap))))


def _by_source(rows: DataFrame, small: DataFrame, *columns: str) -> DataFrame:
    """Columns of a table with a row per source, joined to ``rows``; an uneven source is split by Spark."""
    other = small.select(F.col("source").alias("__own_source"), *columns)
    return rows.join(other, rows["source"].eqNullSafe(F.col("__own_source")), "left").drop("__own_source")


def drawing(line: Column, cap: int, seed: int) -> tuple[Column, Column]:
    """(whole, order) of a document from its row: copies that it has anyway, and its place in the draw for one more (null: none).

    ``line`` is what tells documents apart; the row has size and rate. Equal places are told apart by file and row.
    """
    whole = F.floor(F.col("rate") + 1e-9)
    part = F.col("rate") - whole
    draw = (F.shiftrightunsigned(F.xxhash64(F.lit(seed), line, "size"), 11) + 1) / F.lit(float(1 << 53))
    return whole, F.when((part > 1e-9) & (whole < cap) & (F.col("size") > 0), draw / part)


def _bucket(order: Column) -> Column:
    """Buckets of the order: even ones up to 2, then ever wider ones, as few documents of a small remaining part come early."""
    return F.when(order < 2, F.floor(order * _BUCKETS)).otherwise(2 * _BUCKETS + F.floor((F.log2(order) - 1) * (_BUCKETS // 16)))


def _taken(passes: str = "passes") -> Column:
    """Whether the draw takes a row (order, file, row, size): a pass has it between its ends, and it fitted when the pass began."""
    at = F.struct("order", "file", "row")

    def within(x: Column) -> Column:
        return (F.col("size") <= x["fits"]) & (x["after"].isNull() | (at > x["after"])) & (x["upto"].isNull() | (at <= x["upto"]))

    return F.col("order").isNotNull() & F.coalesce(F.exists(F.col(passes), within), F.lit(False))


class Mix:
    """What decides how often each document is taken: a row per source, and a few documents that settle its sum.

    ``sources``: source, source_size, target, mean, lam, passes; ``settled``: file, row, move. Both are written. With them, copies follow from
    a document's own row, so that no text moves.
    """

    def __init__(self, sources: DataFrame, settled: DataFrame, entropy: str, share: float, cap: int, seed: int):
        self.sources, self.settled, self.entropy, self.share, self.cap, self.seed = sources, settled, entropy, share, cap, seed

    def copies(self, rows: DataFrame) -> DataFrame:
        """``rows`` (with source, size, line, file, row) and source_size, target, copies."""
        rows = _by_source(rows, self.sources, "source_size", "target", "mean", "lam", "passes").withColumn("rate", rate_of(self.entropy, self.share, self.cap))
        whole, order = drawing(F.col("line"), self.cap, self.seed)
        drawn = rows.withColumn("order", order).withColumn("copies", whole + _taken().cast("long"))
        moves = self.settled.select(F.col("file").alias("__own_of_file"), F.col("row").alias("__own_of_row"), "move")
        drawn = drawn.join(moves, (F.col("file") == F.col("__own_of_file")) & (F.col("row") == F.col("__own_of_row")), "left")
        return drawn.withColumn("copies", F.col("copies") + F.coalesce("move", F.lit(0))).drop("__own_of_file", "__own_of_row", "move", "rate", "mean", "lam", "passes", "order")


def _passes(drawn: DataFrame, lacks: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(source, missing) and (source, passes) of the draw from written rows (source, size, file, row, order, bucket) and (source, lacks).

    A pass is a struct (after, upto, fits): from the rows after ``after`` of ``fits`` words or less, those up to ``upto`` are taken, as their
    sum is no more than ``fits``. The row behind ``upto`` is the one that doesn't fit.
    """
    at = F.struct("order", "file", "row")
    place = "struct<order:double,file:string,row:bigint>"
    start = lacks.select("source", F.col("lacks").cast("double").alias("missing"), F.lit(None).cast(place).alias("upto"), F.lit(True).alias("open"))
    now = stage(start.withColumn("passes", F.array().cast(f"array<struct<after:{place},upto:{place},fits:double>>")), "passes")
    run = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    inner = Window.partitionBy("source").orderBy("order", "file", "row").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    while not now.filter("open").isEmpty():
        before = now
        fits = _by_source(drawn, now.filter("open"), "missing", "upto").filter(F.col("missing").isNotNull() & (F.col("size") <= F.col("missing")) & (F.col("upto").isNull() | (at > F.col("upto"))))
        # The bucket in which a source's sum would pass what is missing, and the sum before it.
        buckets = fits.groupBy("source", "bucket").agg(F.sum("size").alias("words"), F.first("missing").alias("missing"))
        buckets = stage(buckets.withColumn("sum", F.sum("words").over(run)), "buckets")
        past = F.col("sum") > F.col("missing")
        reached = buckets.groupBy("source").agg(F.min(F.when(past, F.col("bucket"))).alias("border"), F.coalesce(F.max(F.when(~past, F.col("sum"))), F.lit(0)).alias("before"))
        reached = stage(reached, "reached")
        # Inside it, row by row; without such a bucket all that fits is taken, and the source is done.
        border = _by_source(fits, reached.filter("border is not null"), "border", "before").filter("bucket = border")
        border = border.withColumn("sum", F.col("before") + F.sum("size").over(inner)).withColumn("in", F.col("sum") <= F.col("missing"))
        border = border.groupBy("source").agg(F.max(F.when(F.col("in"), F.col("sum"))).alias("sum"), F.max(F.when(F.col("in"), at)).alias("last"), F.min(F.when(~F.col("in"), at)).alias("next"))
        met = _by_source(_by_source(now, reached.withColumn("any", F.lit(True)), "border", "before", "any"), border, "sum", "last", "next")
        more = F.coalesce("any", F.lit(False))
        words = F.when(more, F.coalesce("sum", "before")).otherwise(F.lit(0))
        # Without a row of the bucket, the pass ends just before the row that doesn't fit.
        this = F.struct(F.col("upto").alias("after"), F.when(F.col("border").isNotNull(), F.coalesce("last", F.struct(F.col("next.order").alias("order"), F.lit("").alias("file"), F.lit(-1).cast("long").alias("row")))).alias("upto"), F.col("missing").alias("fits"))
        now = met.select(
            "source",
            (F.col("missing") - words).alias("missing"),
            F.when(more & F.col("border").isNotNull(), F.col("next")).otherwise(F.col("upto")).alias("upto"),
            (more & F.col("border").isNotNull()).alias("open"),
            F.when(more, F.concat("passes", F.array(this))).otherwise(F.col("passes")).alias("passes"),
        )
        now = stage(now, "passes")
        drop(before, buckets, reached)
    return now.select("source", "missing"), now.select("source", "passes")


def plan(rows: DataFrame, share: float = 1.5, cap: int = 2, weights: tuple[int, ...] = (5, 2, 1), entropy: str = "documents", seed: int = 11, settle: int = 4) -> Mix:
    """Solve for ``rows`` (source, size, line, file, row), which must be written."""
    counts = stage(rows.groupBy("source", "size").agg(F.count("*").alias("n")), "size-counts")
    wanted = stage(targets(counts.groupBy("source").agg(F.sum(F.col("n") * F.col("size")).alias("source_size")), share, cap, weights), "targets")
    tilted = balance(counts, wanted, share, cap, entropy)
    known = ("source_size", "target", "mean", "lam")

    whole = F.floor(rate_of(entropy, share, cap) + 1e-9)
    lacks = _by_source(counts, tilted, *known).groupBy("source").agg((F.first("target") - F.sum(F.col("n") * F.col("size") * whole)).alias("lacks"))
    drawn = _by_source(rows, tilted, *known).withColumn("rate", rate_of(entropy, share, cap))
    whole, order = drawing(F.col("line"), cap, seed)
    drawn = drawn.select("source", "size", "file", "row", whole.alias("whole"), order.alias("order")).filter("order is not null")
    drawn = stage(drawn.withColumn("bucket", _bucket(F.col("order"))), "drawn")

    missing, passes = _passes(drawn, lacks)
    sources = stage(_by_source(tilted.select("source", *known), passes, "passes"), "mix")

    taken = _by_source(drawn, passes, "passes").select("source", "size", "file", "row", "order", (F.col("whole") + _taken().cast("long")).alias("copies"))
    left, settled = missing, None
    for _ in range(settle):
        # The document whose one copy more, or less, brings a source's sum closest to its target.
        moves = F.explode(F.filter(F.array(F.when(F.col("copies") < cap, F.lit(1)), F.when(F.col("copies") > 0, F.lit(-1))), lambda x: x.isNotNull())).alias("move")
        open_ = taken
        if settled is not None:
            done = settled.select(F.col("file").alias("__own_of_file"), F.col("row").alias("__own_of_row"))
            open_ = open_.join(done, (F.col("file") == F.col("__own_of_file")) & (F.col("row") == F.col("__own_of_row")), "left_anti")
        off = F.abs(F.col("missing") - F.col("size") * F.col("move"))
        open_ = _by_source(open_.select("source", "size", "file", "row", "order", moves), left, "missing").filter(off < F.abs("missing"))
        pick = open_.groupBy("source").agg(F.min(F.struct(off.alias("off"), "order", "file", "row", "move", "size")).alias("pick"))
        pick = stage(pick.select("source", "pick.file", "pick.row", "pick.move", (F.col("pick.size") * F.col("pick.move")).alias("more")), "picked")
        if pick.isEmpty():
            break
        settled = pick if settled is None else settled.unionByName(pick)
        left = stage(_by_source(left, pick, "more").select("source", (F.col("missing") - F.coalesce("more", F.lit(0))).alias("missing")), "missing")
    if settled is None:
        settled = rows.sparkSession.createDataFrame([], "source string, file string, row long, move int, more long")
    return Mix(sources, stage(settled.select("file", "row", "move"), "settled"), entropy, share, cap, seed)


def copies(rows: DataFrame, **how) -> DataFrame:
    """From written rows (doc_id, source, size, file, row) to those with source_size, target and copies."""
    return plan(rows, **how).copies(rows)


def mixture(docs: DataFrame) -> DataFrame:
    """Rows (doc_id, size, source_size, target, taken)."""
    return copies(sizes_of(docs)).select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).cast("long").alias("taken"))
