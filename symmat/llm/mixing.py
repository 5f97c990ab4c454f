"""Mixing sources to target weights by capped water-filling, with whole and fractional repetitions (DataFrame functions only).

Targets: the sources share the mix by weight; a source's target is at most ``max_epochs`` times its size, and what it
can't take goes to the others by weight, until none is above its limit. With sources sorted by size / weight, exactly
the first few are at their limit, so the fixed point comes from two running sums instead of a loop.

Taking: a source of target t and size s takes each document floor(t / s) times and, for the rest, once more the
documents that come first in a seeded hash order, up to the one whose end lies nearest to the rest. The place where the
order is cut is found in three steps: among 256 parts of the hash's range, 256 parts of the one that it falls in, and the
rows of the one it falls in there. So a running sum over a source never spans more than 256 rows and a 65,536th of its own.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ._common import cut, unused, word_count

WEIGHTS = (5, 2, 1)
MAX_EPOCHS = 3
SEED = "mix-1"
#: Stands for a null doc_id where rows are ordered.
NO_ID = -(1 << 62)
#: Sources up to which a row of facts a source is sent to all tasks.
SMALL = 100_000


def sized(docs: DataFrame, seed: str = SEED) -> DataFrame:
    """(doc_id, source, size, h) of every row: words, and the seeded hash that orders rows within a source."""
    h = F.md5(F.concat_ws(":", F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit("-"))))
    return docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), h.alias("h"))


def targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """(source, source_size, weight, target) from (source, size); a row per source, null being a source that sorts last.

    Weights go to the sources in code-point order and repeat. Sources without words get target 0.
    """
    per = sizes.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"))
    named = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.pmod(F.row_number().over(named) - 1, F.lit(len(weights))) + 1).cast("int"))
    full = Window.orderBy(F.col("source_size") / F.col("weight"), F.col("source").asc_nulls_last())
    upto, every = full.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy()
    per = (
        per.withColumn("weight", weight)
        .withColumn("total", F.sum("source_size").over(every).cast("double"))
        .withColumn("left", F.col("total") - max_epochs * F.coalesce(F.sum("source_size").over(upto), F.lit(0)))
        .withColumn("open", F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(upto), F.lit(0.0)))
        .withColumn("level", F.col("left") / F.col("open"))
        .withColumn("capped", F.col("level") * F.col("weight") >= max_epochs * F.col("source_size"))
    )
    rest = F.min(F.when(~F.col("capped"), F.struct("at", "level"))).over(every)["level"]
    per = per.withColumn("at", F.row_number().over(full)).withColumn("share", rest)
    return per.select("source", "source_size", "weight", F.when(F.col("capped"), F.col("source_size") * F.lit(float(max_epochs))).otherwise(F.col("share") * F.col("weight")).alias("target"))


def _with(rows: DataFrame, facts: DataFrame) -> DataFrame:
    """``rows`` joined by source with ``facts`` (s, ...), of one row a source; sent to all tasks only where it is known to be small."""
    small = facts.limit(SMALL + 1).count() <= SMALL
    return rows.join(F.broadcast(facts) if small else facts, F.col("source").eqNullSafe(F.col("s")))


def _part_hit(sums: DataFrame, facts: DataFrame) -> DataFrame:
    """(s, part, start, extra): the part of each source of ``sums`` (source, part, words) in which ``extra`` of ``facts`` (s, extra, start) is reached, and the words before it."""
    before = F.coalesce(F.sum("words").over(Window.partitionBy("s").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    placed = _with(sums, facts).withColumn("upto", F.col("start") + before)
    hit = placed.where("extra > upto AND extra <= upto + words + 1e-6")
    # a rest that rounding puts at a part's end may touch two parts: the first decides
    return hit.groupBy("s").agg(F.min(F.struct("part", F.col("upto").alias("start"), "extra")).alias("x")).select("s", "x.*")


def plan(slim: DataFrame, weights: tuple[float, ...] = WEIGHTS, max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """One row per source: source, source_size, target, whole, and cut_h, cut_id: the last row in hash order that is taken once more."""
    goal = cut(targets(slim, weights, max_epochs).withColumn("whole", F.floor(F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0) + 1e-12).cast("long")).withColumn("extra", F.col("target") - F.col("whole") * F.col("source_size")))
    fine = cut(slim.groupBy("source", F.substring("h", 1, 2).alias("a"), F.substring("h", 3, 2).alias("b")).agg(F.sum("size").alias("words")))
    rest = goal.select(F.col("source").alias("s"), "extra").withColumn("start", F.lit(0).cast("long"))
    # of each source's parts, the one that the cut falls in, and the words before it
    coarse = _part_hit(fine.groupBy("source", F.col("a").alias("part")).agg(F.sum("words").alias("words")), rest)
    under = _with(fine, coarse.select("s", F.col("part").alias("a0"))).where("a = a0").select("source", F.concat("a", "b").alias("part"), "words")
    hit = cut(_part_hit(under, coarse.select("s", "extra", "start"))).withColumnsRenamed({"part": "bucket", "start": "before"})
    inside = _with(slim, hit).where(F.substring("h", 1, 4) == F.col("bucket"))
    run = Window.partitionBy("s").orderBy("h", "doc_id")
    ends = inside.select("s", "h", "doc_id", "extra", (F.col("before") + F.sum("size").over(run.rowsBetween(Window.unboundedPreceding, 0))).alias("end"), "size")
    # a row is taken when more than half of it lies before the rest's end
    ends = ends.withColumn("taken", F.col("end") - F.col("size") / 2 <= F.col("extra") + 1e-9)
    id_ = F.coalesce("doc_id", F.lit(NO_ID))
    last = ends.where("taken").groupBy("s").agg(F.max(F.struct("h", id_.alias("id"))).alias("c")).select(F.col("s").alias("s2"), F.col("c.h").alias("cut_h"), F.col("c.id").alias("cut_id"))
    edge = hit.join(last, F.col("s").eqNullSafe(F.col("s2")), "left").select("s", F.coalesce("cut_h", "bucket").alias("cut_h"), F.coalesce("cut_id", F.lit(NO_ID)).alias("cut_id"))
    return cut(goal.join(edge, F.col("source").eqNullSafe(F.col("s")), "left").select("source", "source_size", "target", "whole", "extra", "cut_h", "cut_id"))


def _times(h: str, doc_id: str) -> F.Column:
    id_ = F.coalesce(F.col(doc_id), F.lit(NO_ID))
    more = (F.col(h) < F.col("cut_h")) | ((F.col(h) == F.col("cut_h")) & (id_ <= F.col("cut_id")))
    return F.col("whole") + F.when(F.coalesce(more, F.lit(False)) & (F.col("extra") > 0), 1).otherwise(0)


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, max_epochs: int = MAX_EPOCHS, seed: str = SEED) -> DataFrame:
    """A row per row of ``docs``: doc_id, size, source_size, target, times, taken (= times * size).

    A null text has size 0 and a null source is a source of its own. Equal rows are taken equally often. An empty table
    gives no rows. Memory grows with the number of sources alone.
    """
    slim = cut(sized(docs, seed))
    out = _with(slim, plan(slim, weights, max_epochs).withColumnRenamed("source", "s"))
    return out.select("doc_id", "size", "source_size", "target", _times("h", "doc_id").alias("times")).withColumn("taken", F.col("times") * F.col("size"))


def resample(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, max_epochs: int = MAX_EPOCHS, seed: str = SEED) -> DataFrame:
    """``docs`` with each row repeated as often as the mix takes it; columns stay as they are, whatever their names. Rows without words are kept once."""
    slim = cut(sized(docs, seed))
    names = ("s", "target", "whole", "extra", "cut_h", "cut_id", "own_h", "copies", "copy")
    name = dict(zip(names, unused(docs, *names)))
    goal = plan(slim, weights, max_epochs).select(F.col("source").alias(name["s"]), *[F.col(c).alias(name[c]) for c in names[2:6]])
    h = F.md5(F.concat_ws(":", F.lit(seed), F.coalesce(F.col("doc_id").cast("string"), F.lit("-"))))
    own = docs.withColumn(name["own_h"], h)
    joined = own.join(F.broadcast(goal) if goal.limit(SMALL + 1).count() <= SMALL else goal, F.col("source").eqNullSafe(F.col(name["s"])))
    id_ = F.coalesce(F.col("doc_id"), F.lit(NO_ID))
    more = (F.col(name["own_h"]) < F.col(name["cut_h"])) | ((F.col(name["own_h"]) == F.col(name["cut_h"])) & (id_ <= F.col(name["cut_id"])))
    times = F.col(name["whole"]) + F.when(F.coalesce(more, F.lit(False)) & (F.col(name["extra"]) > 0), 1).otherwise(0)
    times = F.when(F.coalesce(F.col("text").rlike(r"[^\x20\x09-\x0D]"), F.lit(False)), times).otherwise(1)
    counted = joined.withColumn(name["copies"], times.cast("int")).where(F.col(name["copies"]) > 0)
    return counted.withColumn(name["copy"], F.explode(F.sequence(F.lit(1), F.col(name["copies"])))).select(*docs.columns)


#: Rows of op5 in DuckDB.
ORACLE = f"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size,
             md5('{SEED}:' || coalesce(doc_id::VARCHAR, '-')) AS h FROM documents),
 per AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source COLLATE C NULLS LAST) AS rn FROM d GROUP BY source),
 w AS (SELECT *, CASE (rn - 1) % 3 WHEN 0 THEN 5.0::DOUBLE WHEN 1 THEN 2.0 ELSE 1.0 END AS weight FROM per),
 lv AS (SELECT *, row_number() OVER f AS at_,
   ((sum(source_size) OVER ())::DOUBLE - 3 * coalesce(sum(source_size) OVER (f ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::DOUBLE)
   / (sum(weight) OVER () - coalesce(sum(weight) OVER (f ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS level
   FROM w WINDOW f AS (ORDER BY source_size / weight, source NULLS LAST)),
 t AS (SELECT source, source_size, CASE WHEN level * weight >= 3 * source_size THEN source_size * 3.0::DOUBLE
   ELSE (SELECT min_by(level, at_) FROM lv WHERE NOT (level * weight >= 3 * source_size)) * weight END AS target FROM lv),
 g AS (SELECT *, floor(CASE WHEN source_size > 0 THEN target / source_size ELSE 0 END + 1e-12)::BIGINT AS whole FROM t),
 r AS (SELECT d.*, source_size, target, whole, target - whole * source_size AS extra,
   (sum(size) OVER (PARTITION BY d.source ORDER BY h, doc_id ROWS UNBOUNDED PRECEDING))::BIGINT AS ends FROM d JOIN g ON d.source IS NOT DISTINCT FROM g.source)
SELECT doc_id, size, source_size, target, (size * (whole + CASE WHEN extra > 0 AND ends - size / 2.0::DOUBLE <= extra + 1e-9 THEN 1 ELSE 0 END))::BIGINT AS taken FROM r
"""
