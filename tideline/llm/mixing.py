"""Mixing sources to target weights along a time-varying curriculum; DataFrame operations only.

Each source has a weight schedule, piecewise linear over training time 0..1. Its integral is the source's share of
all words; targets are capped at ``max_epochs`` times what the source has, and what is cut off goes to the others by
their shares, so that in the end target = min(cap, level * share). A source's demand up to time t is its target times
the schedule's normalised integral. Its documents, in a fixed pseudo-random order, lie end to end along that demand,
again and again; the inverse of the integral gives the time at which each copy begins, and documents are range-sorted
by that (those that nothing is taken of by a hash, so that they don't share one end).

The running sum within a source never gathers the source: documents fall into buckets of the order's key, bucket
totals are summed over the (small) bucket table, and a window runs within each bucket.

Nulls, empties, repeats: a null text has size 0 and takes nothing. A null source is a source of its own, the last one.
Null ids are ordered after others; repeated rows are documents of their own. A source without words has target 0. An
empty table gives an empty result. Clashing columns don't matter: only the named ones are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from tideline.llm.common import word_count
from tideline.sources.tables import cut

Schedule = list[tuple[float, float]]
#: (time, weight) knots whose integrals are 5, 2 and 1: an early start that fades, an even one, a late rise.
CURRICULUM: list[Schedule] = [[(0.0, 7.0), (1.0, 3.0)], [(0.0, 2.0), (1.0, 2.0)], [(0.0, 0.25), (0.5, 0.75), (1.0, 2.25)]]


def integral(knots: Schedule) -> list[float]:
    """Integral of a schedule from its first knot to each knot."""
    out = [0.0]
    for (a, x), (b, y) in zip(knots, knots[1:]):
        if b <= a or x < 0 or y < 0:
            raise ValueError("knots need rising times and weights of at least 0")
        out.append(out[-1] + (b - a) * (x + y) / 2)
    return out


def time_of(share: Column, knots: Schedule) -> Column:
    """The time at which the schedule's integral has reached ``share`` (0..1) of its whole."""
    total = integral(knots)
    want = share * F.lit(total[-1])
    expr = F.lit(knots[-1][0])
    for (a, x), (b, y), low, high in reversed(list(zip(knots, knots[1:], total, total[1:]))):
        rest, slope = want - F.lit(low), (y - x) / (b - a)
        step = 2 * rest / (F.lit(x) + F.sqrt(F.greatest(F.lit(x * x) + 2 * slope * rest, F.lit(0.0))))
        expr = F.when(want < high, F.lit(a) + F.when(rest > 0, step).otherwise(0.0)).otherwise(expr)
    return expr


def targets(sources: DataFrame, shares: list[float], max_epochs: float) -> DataFrame:
    """``sources`` (``source, source_size, ...``) with its class (0..) and target; one row a source."""
    everything = W.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    before = W.rowsBetween(W.unboundedPreceding, -1)
    order = W.orderBy(F.col("source").asc_nulls_last())
    x = sources.withColumn("class", F.pmod(F.row_number().over(order) - 1, F.lit(len(shares))).cast("int"))
    x = x.withColumn("share", F.element_at(F.array(*map(F.lit, map(float, shares))), F.col("class") + 1)).withColumn("cap", F.col("source_size") * F.lit(float(max_epochs)))
    by = [F.col("cap") / F.col("share"), F.col("source").asc_nulls_last()]
    total, weight = F.sum("source_size").over(W.orderBy(*by).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)), F.sum("share").over(W.orderBy(*by).rowsBetween(W.unboundedPreceding, W.unboundedFollowing))
    cap_before, share_before = (F.coalesce(F.sum(c).over(W.orderBy(*by).rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0)) for c in ("cap", "share"))
    x = x.withColumn("level", (total - cap_before) / (weight - share_before))
    x = x.withColumn("level", F.max(F.when(F.col("level") * F.col("share") <= F.col("cap"), F.col("level"))).over(W.orderBy(*by).rowsBetween(W.unboundedPreceding, W.unboundedFollowing)))
    return x.select("source", "source_size", "class", F.when(F.col("level").isNull(), F.col("cap")).otherwise(F.least("cap", F.col("level") * F.col("share"))).alias("target"))


def _laid(docs: DataFrame, plan: list[Schedule], max_epochs: float, whole: bool, seed: str, id_col: str, text_col: str, source_col: str, carry: list[str]) -> DataFrame:
    """A row for each row of ``docs``: its words, class and place (``at``) in its source, the target, what is taken, and the ``carry`` columns as ``c0, c1, ...``."""
    shares = [integral(k)[-1] for k in plan]
    rows = docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), word_count(F.col(text_col)).alias("size"), F.md5(F.concat(F.lit(seed), F.coalesce(F.col(id_col).cast("string"), F.lit(""))).cast("binary")).alias("key"), *[F.col(c).alias(f"c{i}") for i, c in enumerate(carry)])
    sized = cut(rows.drop(*[f"c{i}" for i in range(len(carry))]))
    per_source = cut(targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), shares, max_epochs))
    n = sized.count()
    # About 128 documents a bucket of all sources together, 65,536 buckets at most; both only shape the plan.
    buckets = max(1, min(65_536, n // 128))
    bucket = F.floor(F.conv(F.substring("key", 1, 8), 16, 10).cast("double") * F.lit(buckets / 2**32)).cast("int")
    sized = sized.withColumn("bucket", bucket)
    sums = sized.groupBy("source", "bucket").agg(F.sum("size").alias("words"))
    starts = sums.withColumn("base", F.coalesce(F.sum("words").over(W.partitionBy("source").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).select("source", "bucket", "base")
    starts = starts.join(per_source.withColumnRenamed("source", "src"), F.col("source").eqNullSafe(F.col("src"))).drop("src")
    # Texts that share an id and a size have the same place in any order; the hash keeps reruns equal.
    ties = [F.xxhash64(*[f"c{i}" for i in range(len(carry))])] if carry else []
    inside = W.partitionBy("source", "bucket").orderBy("key", F.col("doc_id").asc_nulls_last(), "size", *ties).rowsBetween(W.unboundedPreceding, -1)
    laid = (rows.withColumn("bucket", bucket) if carry else sized).withColumn("inner", F.coalesce(F.sum("size").over(inside), F.lit(0)))
    s = starts.withColumnsRenamed({"source": "src", "bucket": "bkt"})
    laid = laid.join(s, F.col("source").eqNullSafe(F.col("src")) & (F.col("bucket") == F.col("bkt"))).withColumn("at", F.col("base") + F.col("inner"))
    budget = F.floor(F.col("target") + 0.5).cast("long")
    rounds = F.when(F.col("source_size") > 0, F.floor(budget / F.col("source_size"))).otherwise(0).cast("long")
    left = budget - rounds * F.col("source_size") - F.col("at")
    part = F.when(F.lit(whole), F.when(2 * left >= F.col("size"), F.col("size")).otherwise(0)).otherwise(F.greatest(F.lit(0), F.least(left, "size")))
    taken = F.when(F.col("size") > 0, F.least(rounds * F.col("size") + part, F.floor(F.col("size") * F.lit(float(max_epochs))))).otherwise(0).cast("long")
    return laid.withColumn("taken", taken)


def _begins(at: Column, plan: list[Schedule]) -> Column:
    """The training time at which the demand of a row's source reaches ``at`` words."""
    when = F.lit(None).cast("double")
    for k, knots in enumerate(plan):
        when = F.when(F.col("class") == k, time_of(F.least(at / F.col("target"), F.lit(1.0)), knots)).otherwise(when)
    return when


def mix(docs: DataFrame, curriculum: list[Schedule] | None = None, max_epochs: float = 3.0, whole: bool = False, seed: str = "mix", id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """``[doc_id, size, source, source_size, target, taken, copies, position]`` for each row, sorted by position.

    ``taken``: words of this document in the mix. The last copy that a source takes is cut where its budget (the target,
    rounded) ends; with ``whole`` a copy is taken or not, by whether its middle lies within the budget.
    ``position``: training time 0..1 of the first copy's begin; null if nothing is taken.
    """
    plan = curriculum or CURRICULUM
    when = _begins(F.col("at"), plan)
    out = _laid(docs, plan, max_epochs, whole, seed, id_col, text_col, source_col, [])
    return out.select("doc_id", "size", "source", "source_size", "target", "taken", F.when(F.col("taken") > 0, F.ceil(F.col("taken") / F.col("size"))).otherwise(0).cast("long").alias("copies"), F.when(F.col("taken") > 0, when).alias("position")).orderBy(F.col("position").asc_nulls_last(), F.xxhash64("doc_id", "size"))


def whole_copies(docs: DataFrame, curriculum: list[Schedule] | None = None, max_epochs: float = 3.0, seed: str = "mix", id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The columns of ``docs``, a row for each whole copy that the mix takes of each row, sorted by the time at which that copy begins.

    Rows are told apart by nothing: they carry their columns through the plan, so null and repeated ids are rows like others.
    """
    plan = curriculum or CURRICULUM
    laid = _laid(docs, plan, max_epochs, True, seed, id_col, text_col, source_col, docs.columns).where("taken > 0")
    each = laid.withColumn("copy", F.explode(F.sequence(F.lit(1), F.ceil(F.col("taken") / F.col("size")).cast("int"))))
    each = each.withColumn("position", _begins(F.col("at") + (F.col("copy") - 1) * F.col("source_size"), plan))
    ordered = each.repartitionByRange("position").sortWithinPartitions("position", "doc_id")
    return ordered.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(docs.columns)])


MIX_SQL = r"""
WITH s AS (
  SELECT doc_id, source, CASE WHEN text IS NULL THEN 0 ELSE len(regexp_extract_all(text, '[^ \t\n\x0B\f\r]+')) END AS size,
         md5('mix' || coalesce(CAST(doc_id AS VARCHAR), '')) AS key
  FROM documents),
src AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM s GROUP BY source),
ranked AS (
  SELECT source, source_size, CASE (row_number() OVER (ORDER BY encode(source) NULLS LAST) - 1) % 3
         WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0::DOUBLE ELSE 1.0::DOUBLE END AS share, source_size * 3.0::DOUBLE AS cap FROM src),
levels AS (
  SELECT *, (sum(source_size::DOUBLE) OVER () - coalesce(sum(cap) OVER w, 0)) / (sum(share) OVER () - coalesce(sum(share) OVER w, 0)) AS level
  FROM ranked WINDOW w AS (ORDER BY cap / share, encode(source) NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
goal AS (
  SELECT source, source_size, least(cap, (SELECT max(level) FROM levels WHERE level * share <= cap) * share) AS target FROM levels),
laid AS (
  SELECT s.*, g.source_size, g.target, CAST(floor(g.target + 0.5) AS BIGINT) AS budget,
         coalesce(sum(size) OVER (PARTITION BY s.source ORDER BY key, doc_id NULLS LAST, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS place
  FROM s JOIN goal g ON s.source IS NOT DISTINCT FROM g.source),
r AS (SELECT *, CASE WHEN source_size > 0 THEN budget // source_size ELSE 0 END AS rounds FROM laid)
SELECT doc_id, CAST(size AS BIGINT) AS size, source_size, target,
       CAST(CASE WHEN size > 0 THEN least(rounds * size + greatest(0, least(budget - rounds * source_size - place, size)), 3 * size) ELSE 0 END AS BIGINT) AS taken
FROM r
"""
