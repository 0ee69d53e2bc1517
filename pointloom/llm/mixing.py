"""Mixing sources to target weights by capped water-filling (native: DataFrame functions only).

Every source gets a share of ``total = budget * all words`` in proportion to its weight; a source stops at
``max_epochs`` times its own words and what it cannot take is shared again by weight until no source is above its
stop. The fixed point has a closed form: with sources in order of stop/weight, those below the water level are
exactly a prefix, so one running sum finds the level.

A source's documents are repeated ``floor(target / size)`` whole times; the fraction left is filled by documents in
the order of a seeded hash, up to the point nearest to the target. The running sum of sizes in hash order is taken
within (source, hash bucket) and added to bucket offsets, so a source that holds a third of all rows is spread
over ``BUCKETS`` groups. The documents themselves (texts) are never shuffled: the plan is one row a source.

Defined cases: null text or a text without words has size 0 and is taken with the whole repetitions only; a null
source is a source of its own, last in order; documents that share an id share the decision; an empty table gives
an empty result; extra columns are carried through by :func:`mix` and ignored by :func:`mix_report`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pointloom.llm.common import WORD_RE, join_lookup, materialize, own_prefix

WEIGHTS = (5, 2, 1)
BUDGET = 1.5
MAX_EPOCHS = 2
#: Hex digits of the hash that name a bucket: 16**3 buckets a source.
BUCKET_DIGITS = 3


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD_RE)), F.lit(0)).cast("long")


def source_key(source: Column) -> Column:
    """A never-null key: null sources meet in one key that no named source has."""
    return F.when(source.isNull(), F.lit("null")).otherwise(F.concat(F.lit("="), source))


def order_hash(doc_id: Column, seed: int) -> Column:
    return F.substring(F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), F.lit("null")))), 1, 16)


def sized(docs: DataFrame, seed: int) -> DataFrame:
    return docs.select(
        "doc_id", F.col("source").cast("string").alias("source"), source_key(F.col("source")).alias("src"),
        n_words(F.col("text")).alias("size"), order_hash(F.col("doc_id"), seed).alias("h"),
    )


def water_fill(sizes: DataFrame, weights=WEIGHTS, budget: float = BUDGET, max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """(src, source, source_size) -> + target. One row a source, so the ordered windows are over a small table."""
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    cycle = F.array(*[F.lit(float(w)) for w in weights])
    ranked = sizes.withColumn("w", F.element_at(cycle, ((F.row_number().over(by_name) - 1) % len(weights) + 1).cast("int")))
    ranked = ranked.withColumn("stop", F.lit(float(max_epochs)) * F.col("source_size"))
    every = Window.partitionBy()
    level = Window.orderBy(F.col("stop") / F.col("w"), F.col("source").asc_nulls_last())
    before = level.rowsBetween(Window.unboundedPreceding, -1)
    ranked = (
        ranked.withColumn("total", F.lit(float(budget)) * F.sum("source_size").over(every))
        .withColumn("w_all", F.sum("w").over(every))
        .withColumn("stop_b", F.coalesce(F.sum("stop").over(before), F.lit(0.0)))
        .withColumn("w_b", F.coalesce(F.sum("w").over(before), F.lit(0.0)))
        .withColumn("water", (F.col("total") - F.col("stop_b")) / (F.col("w_all") - F.col("w_b")))
        .withColumn("full", F.col("stop") <= F.col("water") * F.col("w"))
    )
    # the water level is that of the first source in this order which is not full
    ranked = ranked.withColumn("lvl", F.min(F.when(~F.col("full"), F.struct(F.col("w_b"), F.col("water")))).over(every))
    return ranked.select("src", "source_size", F.when(F.col("full"), F.col("stop")).otherwise(F.col("lvl.water") * F.col("w")).alias("target"))


def mix_plan(sizes: DataFrame, weights=WEIGHTS, budget: float = BUDGET, max_epochs: float = MAX_EPOCHS) -> DataFrame:
    """One row a source: source_size, target, whole repetitions, and the last hash that gets one repetition more."""
    bucketed = sizes.withColumn("bucket", F.substring("h", 1, BUCKET_DIGITS))
    buckets = materialize(bucketed.groupBy("src", "source", "bucket").agg(F.sum("size").alias("words")), sizes.count())
    targets = water_fill(buckets.groupBy("src", "source").agg(F.sum("words").alias("source_size")), weights, budget, max_epochs)
    targets = materialize(
        targets.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(F.lit(0)).cast("int"))
        .withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size"))
    )
    run = Window.partitionBy("src").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    offsets = buckets.withColumn("words_before", F.coalesce(F.sum("words").over(run), F.lit(0)))
    # only the bucket in which the fraction ends needs its documents in order
    ends = join_lookup(offsets, targets, "src").where("words_before <= rest and rest <= words_before + words")
    ends = materialize(ends.select("src", "bucket", "words_before", "rest"))
    inside = Window.partitionBy("src", "bucket").orderBy("h", "size").rowsBetween(Window.unboundedPreceding, 0)
    cut = (
        bucketed.join(ends, ["src", "bucket"])
        .withColumn("upto", F.col("words_before") + F.sum("size").over(inside))
        .where(F.col("upto") - F.col("size") / 2 < F.col("rest"))
        .groupBy("src").agg(F.max("h").alias("cut_in"))
    )
    lower = ends.groupBy("src").agg(F.max("bucket").alias("cut_bucket"))
    return materialize(targets.join(lower, "src", "left").join(cut, "src", "left").select("src", "source_size", "target", "whole", "rest", "cut_bucket", "cut_in"))


def copies_of(h: Column, plan=F.col) -> Column:
    """Repetitions of a document under its source's plan row."""
    before = (F.substring(h, 1, BUCKET_DIGITS) < plan("cut_bucket")) | F.coalesce(h <= plan("cut_in"), F.lit(False))
    return plan("whole") + (plan("cut_bucket").isNotNull() & before & (plan("rest") > 0)).cast("int")


def mix_report(docs: DataFrame, seed: int = 17, **options) -> DataFrame:
    """doc_id, size, source_size, target, taken (words of this document in the mix, repeats counted)."""
    sizes = materialize(sized(docs, seed))
    out = join_lookup(sizes, mix_plan(sizes, **options), "src")
    return out.select("doc_id", "size", F.col("source_size").cast("long").alias("source_size"), "target", (copies_of(F.col("h")) * F.col("size")).cast("long").alias("taken"))


def mix(docs: DataFrame, seed: int = 17, **options) -> DataFrame:
    """The mixed corpus: the rows of ``docs``, each as often as the mix takes it."""
    plan = mix_plan(materialize(sized(docs, seed)), **options)
    src, h, row, copy = (own_prefix(docs) + c for c in ("src", "h", "plan", "copy"))
    keyed = docs.withColumns({src: source_key(F.col("source")), h: order_hash(F.col("doc_id"), seed)})
    plan = plan.select(F.col("src").alias(src), F.struct(*[c for c in plan.columns if c != "src"]).alias(row))
    times = copies_of(F.col(h), lambda c: F.col(row)[c])
    repeated = F.explode(F.when(times > 0, F.sequence(F.lit(1), times)).otherwise(F.array().cast("array<int>")))
    return join_lookup(keyed, plan, src).withColumn(copy, repeated).select(*[docs[c] for c in docs.columns])


ORACLE = r"""
WITH s AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         substr(md5('17:' || coalesce(CAST(doc_id AS VARCHAR), 'null')), 1, 16) AS h
  FROM documents),
src AS (SELECT source, sum(size)::BIGINT AS source_size FROM s GROUP BY source),
w AS (SELECT *, [5.0, 2.0, 1.0][((row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 + 1)::INT]::DOUBLE AS w,
             2.0::DOUBLE * source_size AS stop FROM src),
lev AS (SELECT *, (1.5::DOUBLE * (SELECT sum(source_size) FROM src)::DOUBLE - coalesce(sum(stop) OVER o, 0)) /
                  ((SELECT sum(w) FROM w) - coalesce(sum(w) OVER o, 0)) AS water,
               coalesce(sum(w) OVER o, 0) AS w_b
        FROM w WINDOW o AS (ORDER BY stop / w, source ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
t AS (SELECT source, source_size,
             CASE WHEN stop <= water * w THEN stop
                  ELSE w * (SELECT arg_min(water, w_b) FROM lev WHERE stop > water * w) END AS target FROM lev),
p AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::INT ELSE 0 END AS whole FROM t),
r AS (SELECT s.doc_id, s.size, p.source_size, p.target, p.whole, p.target - p.whole * p.source_size AS rest,
             sum(s.size) OVER (PARTITION BY s.source ORDER BY s.h, s.size ROWS UNBOUNDED PRECEDING)::BIGINT AS upto
      FROM s JOIN p ON s.source IS NOT DISTINCT FROM p.source)
SELECT doc_id, size, source_size, target,
       ((whole + CASE WHEN rest > 0 AND upto - size / 2.0::DOUBLE < rest THEN 1 ELSE 0 END) * size)::BIGINT AS taken FROM r
"""
