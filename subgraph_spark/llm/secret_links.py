"""Secrets in texts, with multipart credential linking, in DataFrame operations alone.

Base findings stand by themselves: an assignment to a secret's name, an access identifier, a long run of hex digits.
Weak candidates do not: identifiers of less certain prefixes, bare strings that could be a secret key, and endpoints. They
are reported only where complementary parts co-occur: parts of a text are joined to those whose ends are within ``reach`` code
points of theirs, and an identifier needs a secret there, a secret an identifier, an endpoint both.

The interval join is a window over ranges of positions, so a part meets its neighbourhood's counts and not each neighbour. It sees
the texts' parts only, and of these only texts that have a weak candidate beside another kind. A scope is a
text, cut into stretches of ``stretch`` code points: windows overlap the cuts, so that a text full of parts is many small groups.

Defined cases: a null text is empty; null and repeated ids are kept, one row per row; an empty table gives no rows; other
columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stage, whole_text

#: The base kinds, in the order in which they are listed.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{12,}"  # a run that is too short has no longer one inside it
HEX = r"[0-9a-f]{32,}"
ASSIGN_LEAST = 8

#: Weak kinds.
IDENTIFIER = r"\b(?:ASIA|ABIA|ACCA|AROA|AIDA|AGPA|ANPA)[A-Z0-9]{12,}"
BARE = r"(?<![A-Za-z0-9+/=])[A-Za-z0-9+/]{40}(?![A-Za-z0-9+/=])"
ENDPOINT = r"https?://[A-Za-z0-9.-]+(?::[0-9]+)?|[a-z0-9-]+(?:\.[a-z0-9-]+)*\.amazonaws\.com"
KINDS = ("assign", "access", "hex", "identifier", "bare", "endpoint")
_SPANS = "array<struct<start:bigint,end:bigint>>"
#: Matches whose places are added up one by one.
_BLOCK = 256


def _step(s: Column, x: Column) -> Column:
    """Go on by a gap and a match, which is kept or not."""
    begin = s["at"] + x["gap"]
    one = F.struct(begin.alias("start"), (begin + x["run"]).alias("end"))
    return F.struct((begin + x["run"]).alias("at"), F.when(x["kept"], F.array_append(s["found"], one)).otherwise(s["found"]).alias("found"))


def spans(text: Column, pattern: str, group: int = 0, least: int = 0) -> Column:
    """Start and end, in code points, of the leftmost non-overlapping matches whose ``group`` has ``least`` characters.

    What lies between matches comes from a split, the matches from an extraction; lengths add up to places.
    """
    between = F.split(text, pattern, -1)
    lengths = F.transform(F.regexp_extract_all(text, F.lit(pattern), F.lit(0)), lambda x: F.length(x).cast("long"))
    kept = F.transform(F.regexp_extract_all(text, F.lit(pattern), F.lit(group)), lambda x: F.length(x) >= least) if least else F.transform(lengths, lambda _: F.lit(True))
    parts = F.zip_with(F.zip_with(F.slice(F.transform(between, lambda x: F.length(x).cast("long")), 1, F.size(lengths)), lengths, lambda a, b: F.struct(a.alias("gap"), b.alias("run"))), kept, lambda x, k: F.struct(x["gap"].alias("gap"), x["run"].alias("run"), k.alias("kept")))
    # Places add up within blocks first and over the blocks then, so that no long array grows one by one.
    blocks = F.transform(F.sequence(F.lit(0), F.greatest(F.size(lengths) - 1, F.lit(0)), F.lit(_BLOCK)), lambda at: F.aggregate(F.slice(parts, at + 1, _BLOCK), F.struct(F.lit(0).cast("long").alias("at"), F.array().cast(_SPANS).alias("found")), _step))
    none = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast(f"array<{_SPANS}>").alias("found"))
    moved = lambda s, x: F.transform(x["found"], lambda y: F.struct((y["start"] + s["at"]).alias("start"), (y["end"] + s["at"]).alias("end")))
    grown = F.flatten(F.aggregate(blocks, none, lambda s, x: F.struct((s["at"] + x["at"]).alias("at"), F.array_append(s["found"], moved(s, x)).alias("found")), lambda s: s["found"]))
    return F.when(text.rlike(pattern), grown).otherwise(F.array().cast(_SPANS))


def _tagged(column: str, kind: int) -> Column:
    return F.transform(column, lambda x: F.struct(x["start"].alias("start"), F.lit(kind).alias("kind"), x["end"].alias("end")))


def _joined(found: Column) -> Column:
    """kind:start:end by start, then kind, comma-joined."""
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(F.array_sort(found), lambda x: F.concat_ws(":", F.element_at(names, x["kind"] + 1), x["start"].cast("string"), x["end"].cast("string"))), ",")


def find_secrets(docs: DataFrame, reach: int = 400, stretch: int = 20_000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (doc_id, base, weak, reported): arrays of (start, kind, end), kind an index of KINDS."""
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), whole_text(text_col).alias("text"))
    text = F.col("text")
    rows = rows.select("doc_id", "text", spans(text, ASSIGN, 2, ASSIGN_LEAST).alias("assign"), spans(text, ACCESS).alias("access"), spans(text, HEX).alias("hex"), spans(text, IDENTIFIER).alias("identifier"))
    # Bare strings need an identifier; endpoints need one too, and a secret.
    rows = rows.withColumn("bare", F.when(F.size("access") + F.size("identifier") > 0, spans(text, BARE)).otherwise(F.array().cast(_SPANS)))
    some = (F.size("access") + F.size("identifier") > 0) & (F.size("assign") + F.size("hex") + F.size("bare") > 0)
    rows = rows.withColumn("endpoint", F.when(some, spans(text, ENDPOINT)).otherwise(F.array().cast(_SPANS)))
    base = F.concat(*[_tagged(k, i) for i, k in enumerate(KINDS[:3])])
    weak = F.concat(*[_tagged(k, i) for i, k in enumerate(KINDS[3:], 3)])
    rows = stage(rows.select(F.monotonically_increasing_id().alias("line"), "doc_id", base.alias("base"), weak.alias("weak")), "secret-parts")  # from here on, lines are fixed and texts are left behind

    parts = rows.filter(F.size("weak") > 0).select("line", F.explode(F.concat("base", "weak")).alias("part")).select("line", "part.start", "part.kind", "part.end")
    # A weak span inside a base one, or over one, is that finding: a base span before it ends behind its start, or one begins before its end.
    by_place = Window.partitionBy("line").orderBy("start")
    base_end, base_start = F.when(F.col("kind") < 3, F.col("end")), F.when(F.col("kind") < 3, F.col("start"))
    reached = F.max(base_end).over(by_place.rangeBetween(Window.unboundedPreceding, Window.currentRow))
    begun = F.min(base_start).over(by_place.rangeBetween(Window.currentRow, Window.unboundedFollowing))
    parts = parts.select("*", reached.alias("reached"), begun.alias("begun")).filter((F.col("kind") < 3) | (F.coalesce("reached", "start") <= F.col("start")) & (F.coalesce("begun", "end") >= F.col("end"))).drop("reached", "begun")
    # A part counts at its start and at its end, in the stretch of each, and is seen from the ones next to it.
    points = parts.select("line", "start", "kind", "end", F.explode(F.array("start", "end")).alias("at"))
    own = F.floor(F.col("at") / stretch)
    seen = F.array_distinct(F.array(own, F.floor(F.greatest(F.col("at") - reach, F.lit(0)) / stretch), F.floor((F.col("at") + reach) / stretch)))
    points = points.select("*", own.alias("own"), F.explode(seen).alias("cut"))
    around = Window.partitionBy("line", "cut").orderBy("at").rangeBetween(-reach, reach)
    met = lambda *kinds: F.count_if(F.col("kind").isin(*kinds)).over(around) > 0
    linked = points.select("line", "start", "kind", "end", "own", "cut", met(1, 3).alias("identifier"), met(0, 2, 4).alias("secret")).filter("own = cut and kind >= 3")
    linked = linked.groupBy("line", "start", "kind", "end").agg(F.max("identifier").alias("identifier"), F.max("secret").alias("secret"))
    linked = linked.filter(F.when(F.col("kind") == 3, F.col("secret")).when(F.col("kind") == 4, F.col("identifier")).otherwise(F.col("identifier") & F.col("secret")))
    linked = linked.groupBy("line").agg(F.collect_list(F.struct("start", "kind", "end")).alias("reported"))
    return rows.join(linked, "line", "left").select("doc_id", "base", "weak", F.coalesce("reported", F.filter("weak", lambda _: F.lit(False))).alias("reported"))


def secret_report(docs: DataFrame) -> DataFrame:
    """Counts, digest and text form of what ``find_secrets`` finds."""
    found = find_secrets(docs)
    n = lambda kind: F.size(F.filter("base", lambda x: x["kind"] == kind)).cast("long")
    return found.select("doc_id", n(0).alias("n_assign"), n(1).alias("n_access"), n(2).alias("n_hex"), F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(F.concat("base", "reported")).alias("spans"))
