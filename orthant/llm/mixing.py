"""Mixing sources to target weights (1) by Pareto order sampling, in DataFrame operations alone.

A source's target over its size is the number of copies each of its words is owed. The whole part is
certain: every document gets that many copies. The rest is a probability p < 1, for which documents are
ranked by random odds over inclusion odds, (u / (1 - u)) / (p / (1 - p)), u a hash of the document's id.
The sample is fixed in size, in words: documents are taken in rank order as long as the words owed last,
and one more document, the one whose size is nearest to what is still owed, closes most of the rest. Of rows with
one id and size, which share a rank, as many are taken as are owed; only such rows at the cut are numbered.

The cut in rank order is found without sorting a source in one task: words are summed by coarse, then
fine classes of the rank's logarithm, and only the one fine class in which the words owed run out is put
in order. Each source is described by one row; up to ``BROADCAST_SOURCES`` of them are broadcast.

Defined cases: a null or empty text has size 0, takes 0; a null source is a source of its own, last in
order; null ids are ids like others; the rank depends on id and size alone; of repeated rows
with both alike any may be taken, but as many in every rerun; an empty table gives an empty result; if all sizes
are 0, all targets are 0. Extra columns are handed on by ``mixed_documents``, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import materialize

WORD = r"[^\x20\x09-\x0D]+"
#: Sources whose table may be broadcast; more are joined by a shuffle.
BROADCAST_SOURCES = 50_000


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def unit_hash(key: Column) -> Column:
    """A number in (0, 1) from the first 52 bits of md5."""
    return (F.conv(F.substring(F.md5(key.cast("binary")), 1, 13), 16, 10).cast("long").cast("double") + F.lit(0.5)) / F.lit(float(1 << 52))


def source_targets(sizes: DataFrame, weights: tuple[int, ...], share: float, most: float) -> DataFrame:
    """(source, source_size, target) from (source, source_size): weights go round in code point order, null
    last; ``share`` times all words are dealt by weight; a source's target stops at ``most`` times its size
    and the rest is dealt again. The level at which that ends is found from the sources in order of the
    level at which each is full."""
    everyone = Window.partitionBy(F.lit(0))
    cycle = F.element_at(F.array(*(F.lit(float(w)) for w in weights)), (F.pmod(F.col("place") - 1, F.lit(len(weights))) + 1).cast("int"))
    filling = everyone.orderBy("full_at", "place")
    before = filling.rowsBetween(Window.unboundedPreceding, -1)
    return (
        sizes.withColumn("place", F.row_number().over(everyone.orderBy(F.col("source").asc_nulls_last())))
        .withColumn("weight", cycle).withColumn("cap", F.col("source_size") * F.lit(most)).withColumn("full_at", F.col("cap") / F.col("weight"))
        .withColumn("budget", F.sum("source_size").over(everyone) * F.lit(share)).withColumn("all_weight", F.sum("weight").over(everyone))
        .withColumn("level", (F.col("budget") - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / (F.col("all_weight") - F.coalesce(F.sum("weight").over(before), F.lit(0.0))))
        .withColumn("final", F.min(F.when(F.col("cap") > F.col("weight") * F.col("level"), F.struct("full_at", "place", "level"))).over(everyone)["level"])
        .select("source", "source_size", F.when(F.col("final").isNull(), F.col("cap")).otherwise(F.least(F.col("cap"), F.col("weight") * F.col("final"))).alias("target"))
    )


def _u() -> Column:
    return unit_hash(F.concat(F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.lit(":"), F.col("size").cast("string")))


def copies_plan(sized: DataFrame, targets: DataFrame) -> DataFrame:
    """One row per source that tells which of its documents get how many copies. ``sized`` (doc_id, source,
    size) and ``targets`` are written tables."""
    few = targets.count() <= BROADCAST_SOURCES
    by_source = lambda x: F.broadcast(x) if few else x
    plan = (
        targets.withColumn("rate", F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0))
        .withColumn("whole", F.floor("rate").cast("long")).withColumn("p", F.col("rate") - F.col("whole"))
        .withColumn("owed", F.col("target") - F.col("whole") * F.col("source_size"))
        .withColumnRenamed("source", "of")
    )

    def ranked(params: DataFrame) -> DataFrame:
        return (
            sized.join(by_source(params), F.col("source").eqNullSafe(F.col("of"))).where("p > 0 and size > 0")
            .withColumn("u", _u()).withColumn("odds", F.col("u") / (1 - F.col("u")) * ((1 - F.col("p")) / F.col("p")))
            .withColumn("fine", F.floor((F.log("odds") + 100.0) * 16 * 4096).cast("long")).withColumn("coarse", F.shiftright("fine", 12))
        )

    def cut(rows: DataFrame, column: str, params: DataFrame, spent: str) -> DataFrame:
        """The class of ``column`` in which the words owed run out, and the words that the classes before it take."""
        run = Window.partitionBy("of").orderBy(column)
        sums = rows.groupBy("of", column).agg(F.sum("size").alias("words")).withColumn("until", F.sum("words").over(run))
        joined = sums.join(by_source(params.select(F.col("of").alias("of2"), "owed", spent)), F.col("of").eqNullSafe(F.col("of2")))
        return joined.where(F.col("until") + F.col(spent) > F.col("owed")).groupBy("of").agg(F.min(F.struct(F.col(column), (F.col("until") - F.col("words") + F.col(spent)).alias("spent"))).alias("first")).select(F.col("of").alias("of3"), f"first.{column}", "first.spent")

    zero = plan.withColumn("spent0", F.lit(0).cast("long"))
    level1 = cut(ranked(plan), "coarse", zero, "spent0").select("of3", F.col("coarse").alias("cut1"), F.col("spent").alias("spent1"))
    plan1 = materialize(plan.join(level1, F.col("of").eqNullSafe(F.col("of3")), "left").drop("of3"), "mix-coarse")
    level2 = cut(ranked(plan1).where("coarse = cut1"), "fine", plan1, "spent1").select("of3", F.col("fine").alias("cut2"), F.col("spent").alias("spent2"))
    plan2 = materialize(plan1.join(level2, F.col("of").eqNullSafe(F.col("of3")), "left").drop("of3"), "mix-fine")
    place = F.struct("odds", "doc_id", "size")
    # rows of one place are alike: the first place that doesn't fit in whole gives some of its rows
    inside = ranked(plan2).where("fine = cut2").groupBy("of", "owed", "spent2", place.alias("place")).agg(F.count("*").alias("mates"))
    words = F.col("place.size") * F.col("mates")
    inside = inside.withColumn("until", F.sum(words).over(Window.partitionBy("of").orderBy("place")) + F.col("spent2"))
    fits = F.col("until") <= F.col("owed")
    part = F.floor((F.col("owed") - F.col("until") + words) / F.col("place.size")).cast("long")
    last = inside.groupBy(F.col("of").alias("of3")).agg(F.max(F.when(fits, F.col("place"))).alias("last"), F.max(F.when(fits, F.col("until"))).alias("spent3"), F.min(F.when(~fits, F.struct("place", part.alias("take"), "mates"))).alias("edge"))
    left = F.col("owed") - F.coalesce("spent3", "spent2", F.lit(0)) - F.coalesce(F.col("edge.take") * F.col("edge.place.size"), F.lit(0))
    plan3 = materialize(plan2.join(last, F.col("of").eqNullSafe(F.col("of3")), "left").drop("of3").withColumn("rest", left), "mix-cut")
    gap = F.abs(F.col("size") - F.col("rest"))
    close = ranked(plan3).where(~_in_order() & (gap < F.col("rest"))).groupBy("of", "odds", "doc_id", "size", gap.alias("gap"), "edge").agg(F.count("*").alias("mates"))
    # rows at the edge that are all taken are no candidates
    spare = F.col("mates") > F.when(F.coalesce(place == F.col("edge.place"), F.lit(False)), F.col("edge.take")).otherwise(0)
    close = close.where(spare).groupBy("of").agg(F.min(F.struct("gap", "odds", "doc_id", "size", "mates")).alias("extra"))
    extra = close.select(F.col("of").alias("of3"), F.struct(F.struct("extra.odds", "extra.doc_id", "extra.size").alias("place"), F.lit(1).cast("long").alias("take"), F.col("extra.mates").alias("mates")).alias("extra"))
    return materialize(plan3.join(extra, F.col("of").eqNullSafe(F.col("of3")), "left").drop("of3"), "mix-plan")


def _in_order() -> Column:
    place = F.struct("odds", "doc_id", "size")
    return F.coalesce((F.col("fine") < F.col("cut2")) | ((F.col("fine") == F.col("cut2")) & F.coalesce(place <= F.col("last"), F.lit(False))), F.lit(False))


def with_copies(sized: DataFrame, plan: DataFrame, few: bool) -> DataFrame:
    """``sized`` (doc_id, source, size and more) with source_size, target and copies."""
    u, p = _u(), F.col("p")
    here = lambda e: F.coalesce(F.struct("odds", "doc_id", "size") == F.col(f"{e}.place"), F.lit(False))
    take = F.when(here("edge"), F.col("edge.take")).otherwise(0) + F.when(here("extra"), 1).otherwise(0)
    mates = F.greatest(F.when(here("edge"), F.col("edge.mates")), F.when(here("extra"), F.col("extra.mates")), F.lit(1))
    marked = (
        sized.join(F.broadcast(plan) if few else plan, F.col("source").eqNullSafe(F.col("of")))
        .withColumn("odds", F.when(p > 0, u / (1 - u) * ((1 - p) / F.when(p > 0, p).otherwise(1.0))))
        .withColumn("fine", F.floor((F.log("odds") + 100.0) * 16 * 4096).cast("long"))
        .withColumn("live", (p > 0) & (F.col("size") > 0)).withColumn("take", F.when(F.col("live"), take).otherwise(0)).withColumn("mates", F.when(F.col("live"), mates).otherwise(1))
    )

    def done(rows: DataFrame, sampled: Column) -> DataFrame:
        return rows.select(*sized.columns, "source_size", "target", (F.col("whole") + F.when(F.col("live") & (_in_order() | sampled), 1).otherwise(0)).cast("long").alias("copies"))

    if plan.where("edge.mates > 1 or extra.mates > 1").isEmpty():
        return done(marked, F.col("take") > 0)
    # rows alike at a cut are numbered within their partitions, from the numbers of those in the partitions before
    group = F.xxhash64(F.col("of").isNull(), "of", "odds", F.col("doc_id").isNull(), "doc_id", "size")
    alike = marked.where("mates > 1 and take > 0").withColumn("alike", group).withColumn("rid", F.monotonically_increasing_id())
    alike = materialize(alike.withColumn("part", F.shiftright("rid", 33)), "mix-alike")
    before = alike.groupBy("alike", "part").agg(F.count("*").alias("n")).withColumn("head", F.sum("n").over(Window.partitionBy("alike").orderBy("part")) - F.col("n")).drop("n")
    numbered = alike.withColumn("number", F.row_number().over(Window.partitionBy("alike", "part").orderBy("rid"))).join(before, ["alike", "part"])
    return done(marked.where("mates = 1 or take = 0"), F.col("take") > 0).unionByName(done(numbered, F.col("number") + F.col("head") <= F.col("take")))


def plan_of(documents: DataFrame, weights: tuple[int, ...], share: float, most: float) -> tuple[DataFrame, DataFrame, bool]:
    """(doc_id, source, size of every row; the plan by source; whether the plan may be broadcast)."""
    sized = materialize(documents.select("doc_id", "source", word_count(F.col("text")).alias("size")), "mix-sizes")
    targets = materialize(source_targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, share, most), "mix-targets")
    return sized, copies_plan(sized, targets), targets.count() <= BROADCAST_SOURCES


WEIGHTS, TOTAL_SHARE, MOST_COPIES = (3, 1, 2), 1.5, 2.0


def taken_words(documents: DataFrame) -> DataFrame:
    """doc_id, size, source_size, target, taken for every row of ``documents``."""
    out = with_copies(*plan_of(documents, WEIGHTS, TOTAL_SHARE, MOST_COPIES))
    return out.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).alias("taken"))


def mixed_documents(documents: DataFrame) -> DataFrame:
    """The rows of the mix, each as often as it is taken, with the columns of ``documents``. A text without
    words takes nothing and comes as often as its source's certain copies."""
    _, plan, few = plan_of(documents, WEIGHTS, TOTAL_SHARE, MOST_COPIES)
    whole = F.struct(*(F.col(f"`{c}`") for c in documents.columns)).alias("row")
    out = with_copies(documents.select(whole, "doc_id", "source", word_count(F.col("text")).alias("size")), plan, few)
    out = out.where("copies > 0").select("row", F.explode(F.sequence(F.lit(1).cast("long"), "copies")).alias("copy"))
    return out.select(*(F.col("row")[c].alias(c) for c in documents.columns))


ORACLE = r"""
WITH sized AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size FROM documents
), totals AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sized GROUP BY source
), placed AS (
  SELECT *, row_number() OVER (ORDER BY source ASC NULLS LAST) AS place FROM totals
), weighed AS (
  SELECT *, CASE (place - 1) % 3 WHEN 0 THEN 3.0::DOUBLE WHEN 1 THEN 1.0::DOUBLE ELSE 2.0::DOUBLE END AS weight, source_size * 2.0::DOUBLE AS cap FROM placed
), levels AS (
  SELECT *, (CAST(sum(source_size) OVER () AS BIGINT) * 1.5::DOUBLE
             - coalesce(sum(cap) OVER (ORDER BY cap / weight, place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0::DOUBLE))
            / (sum(weight) OVER () - coalesce(sum(weight) OVER (ORDER BY cap / weight, place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0::DOUBLE)) AS level
  FROM weighed
), final AS (
  SELECT level FROM levels WHERE cap > weight * level ORDER BY cap / weight, place LIMIT 1
), targets AS (
  SELECT source, source_size, coalesce(least(cap, weight * (SELECT level FROM final)), cap) AS target FROM levels
), plan AS (
  SELECT *, CASE WHEN source_size > 0 THEN target / source_size ELSE 0.0::DOUBLE END AS rate FROM targets
), odds AS (
  SELECT d.doc_id, d.source, d.size, p.source_size, p.target, CAST(floor(rate) AS BIGINT) AS whole, rate - floor(rate) AS p,
         p.target - CAST(floor(rate) AS BIGINT) * p.source_size AS owed,
         (CAST('0x' || substr(md5(coalesce(CAST(d.doc_id AS VARCHAR), '') || ':' || CAST(d.size AS VARCHAR)), 1, 13) AS BIGINT)::DOUBLE + 0.5) / 4503599627370496.0::DOUBLE AS u
  FROM sized d JOIN plan p ON d.source IS NOT DISTINCT FROM p.source
), ranked AS (
  SELECT *, CASE WHEN p > 0 THEN u / (1 - u) * ((1 - p) / p) END AS rank_value FROM odds
), running AS (
  SELECT *, sum(CASE WHEN p > 0 THEN size ELSE 0 END) OVER (PARTITION BY source ORDER BY rank_value, doc_id, size ROWS UNBOUNDED PRECEDING) AS until FROM ranked
), chosen AS (
  SELECT *, p > 0 AND size > 0 AND until <= owed AS taken_in_order FROM running
), rest AS (
  SELECT *, owed - coalesce(sum(CASE WHEN taken_in_order THEN size END) OVER (PARTITION BY source), 0) AS rest FROM chosen
), closing AS (
  SELECT *, p > 0 AND size > 0 AND NOT taken_in_order AND abs(size - rest) < rest AS may_close,
         row_number() OVER (PARTITION BY source, (p > 0 AND size > 0 AND NOT taken_in_order AND abs(size - rest) < rest) ORDER BY abs(size - rest), rank_value, doc_id, size) AS turn
  FROM rest
)
SELECT doc_id, size, source_size, target, size * (whole + CASE WHEN taken_in_order OR (may_close AND turn = 1) THEN 1 ELSE 0 END) AS taken FROM closing
"""
