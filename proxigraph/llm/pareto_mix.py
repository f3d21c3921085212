"""Mixing sources to target weights by Pareto order sampling.

Every source gets a target in words; a document is first taken as often as its whole expected
number of copies. What is missing to the target is a fixed-size sample of unequal probabilities:
documents are ranked by their random odds u / (1 - u) divided by their inclusion odds, and taken from
the lowest rank on until the words come nearest to the target. Inclusion odds are the source's odds
times the document's size over the source's mean size: words are what a target counts, and long
documents come early in the ranking, so that short ones are left to meet the target closely. The
ranking of a source is cut by two levels of 4096
buckets of the rank variable: only sums per bucket are grouped, and only the documents of the one
bucket in which the target falls are sorted, so a source may hold any share of the rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from proxigraph.runtime import broadcast_if_small, settle

WEIGHTS = (5, 2, 1)
SHARE = 1.5
MOST_COPIES = 2
SEED = 42
BUCKETS = 4096
#: Column with how often a row is taken.
TIMES = "_mx_times"
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: str = "text") -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def uniform(seed: int) -> Column:
    """A number in (0, 1) that depends on seed and doc_id only."""
    digest = F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))))
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("long") + F.lit(0.5)) / F.lit(float(1 << 52))


def targets(sizes: DataFrame, weights=WEIGHTS, share: float = SHARE, most: int = MOST_COPIES) -> DataFrame:
    """sizes(source, size) -> one row per source: source_size, its mean, target, copies (whole ones) and part.

    Sources in code point order, null last, take the weights in turn. With sources ordered by what
    they can give per unit of weight, the common level of those that are not exhausted is the
    largest that any prefix of exhausted sources leaves for the others. The windows run over the
    aggregated table of sources only.
    """
    by_name = Window.orderBy(F.col("source").asc_nulls_last())
    table = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), (F.sum("size") / F.count("*")).alias("mean")).withColumn("n", F.row_number().over(by_name) - 1)
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), F.col("n") % len(weights) + 1)
    table = table.withColumn("weight", weight).withColumn("cap", F.col("source_size") * F.lit(float(most)))
    fill = Window.orderBy(F.col("cap") / F.col("weight"), "n")
    spent = F.sum("cap").over(fill.rowsBetween(Window.unboundedPreceding, 0)) - F.col("cap")
    rest = F.sum("weight").over(fill.rowsBetween(0, Window.unboundedFollowing))
    every = Window.orderBy("n").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    table = table.withColumn("level", (F.sum("source_size").over(every) * F.lit(float(share)) - spent) / rest)
    table = table.withColumn("target", F.least("cap", F.col("weight") * F.max("level").over(every)))
    ratio = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    return table.withColumn("copies", F.floor(ratio).cast("long")).select(
        "source", "source_size", "mean", "target", "copies", (ratio - F.floor(ratio)).alias("part"),
        (F.col("target") - F.floor(ratio) * F.col("source_size")).alias("extra"),
    )


def _join(rows: DataFrame, table: DataFrame) -> DataFrame:
    """Inner join on source, in which null equals null."""
    other = table.withColumnRenamed("source", "_mx_source")
    return rows.join(other, rows["source"].eqNullSafe(other["_mx_source"])).drop("_mx_source")


def _boundary(rows: DataFrame, bucket: str, before: str, found: str) -> DataFrame:
    """Per source, the bucket in which the running sum of sizes passes `extra`, and the sum before it."""
    run = Window.partitionBy("source").orderBy(bucket)
    sums = rows.groupBy("source", "_mx_extra", before, bucket).agg(F.sum("size").alias("words"))
    sums = sums.withColumn("upto", F.col(before) + F.sum("words").over(run))
    low = sums.filter("upto >= _mx_extra").groupBy("source").agg(F.min(F.struct(bucket, (F.col("upto") - F.col("words")).alias("b"))).alias("x"))
    return low.select("source", F.col(f"x.{bucket}").alias(found), F.col("x.b").alias(f"{found}_before"))


def mix(docs: DataFrame, weights=WEIGHTS, share: float = SHARE, most: int = MOST_COPIES, seed: int = SEED, boost: Column | None = None) -> DataFrame:
    """docs (doc_id, source, text or size, ...) plus size, source_size, target and taken (words).

    A null text has size 0; rows with a null source form a source of their own; rows of one doc_id
    share their random number, and those of one size rank next to each other; an empty table gives an
    empty result. boost multiplies the inclusion odds of single documents.
    Columns of docs with the new names are replaced, but for size, which is used if there, and the
    column named by TIMES says how often a row is taken.
    """
    rows = docs.drop("source_size", "target", "taken")
    if "size" not in rows.columns:
        rows = rows.withColumn("size", word_count())
    narrow = settle(rows.select("doc_id", "source", "size", *([boost.alias("_mx_boost")] if boost is not None else [])), "mix-sizes")
    goal = targets(narrow, weights, share, most)
    goal = goal.select("source", "source_size", "target", *[F.col(c).alias(f"_mx_{c}") for c in ("mean", "copies", "part", "extra")])
    goal = broadcast_if_small(settle(goal, "mix-targets"))  # one row a source

    def ranked(frame: DataFrame, more: Column | None) -> DataFrame:
        """The frame with its rank variable: random odds over inclusion odds, mapped to [0, 1) in the same
        order (1 for a document that no sample can hold), and the buckets of two levels. A column a step,
        as what a later step uses twice is not computed twice then."""
        lift = F.when(F.col("_mx_mean") > 0, F.col("size") / F.col("_mx_mean")).otherwise(F.lit(0.0))
        part, u, q, scaled = F.col("_mx_part"), F.col("_mx_u"), F.col("_mx_q"), F.col("_mx_t") * BUCKETS
        out = _join(frame, goal).withColumn("_mx_u", uniform(seed)).withColumn("_mx_lift", lift if more is None else lift * more)
        out = out.withColumn("_mx_q", F.when((part > 0) & (F.col("_mx_lift") > 0), (u / (F.lit(1.0) - u)) / (part / (F.lit(1.0) - part) * F.col("_mx_lift"))))
        out = out.withColumn("_mx_t", F.coalesce(q / (F.lit(1.0) + q), F.lit(1.0))).drop("_mx_u", "_mx_lift", "_mx_q")
        out = out.withColumn("_mx_b1", F.floor(scaled)).withColumn("_mx_b2", F.floor((scaled - F.col("_mx_b1")) * BUCKETS))
        # a filter that reads this column stays above it, so it does not repeat the expressions below
        return out.withColumn("_mx_stop", F.monotonically_increasing_id())

    sampled = ranked(narrow, None if boost is None else F.col("_mx_boost")).filter("_mx_part > 0")
    sampled = sampled.select("source", "size", "_mx_extra", "_mx_b1", "_mx_b2", F.lit(0).cast("long").alias("_mx_zero"))
    cut = broadcast_if_small(settle(_boundary(sampled, "_mx_b1", "_mx_zero", "_mx_c1"), "mix-cut"))
    inner = _join(sampled, cut).filter("_mx_b1 = _mx_c1")
    cut = _join(cut, settle(_boundary(inner, "_mx_b2", "_mx_c1_before", "_mx_c2"), "mix-cut")).select("source", "_mx_c1", "_mx_c2", "_mx_c2_before")
    cut = broadcast_if_small(settle(cut, "mix-cut"))

    # a source without a boundary has no part to sample
    other = cut.withColumnRenamed("source", "_mx_source")
    full = ranked(rows, boost)
    full = full.join(other, full["source"].eqNullSafe(other["_mx_source"]), "left").drop("_mx_source")
    known, extra, upto = F.col("_mx_c1").isNotNull(), F.col("_mx_extra"), F.col("_mx_upto")
    edge = known & (F.col("_mx_stop") >= 0) & (F.col("_mx_b1") == F.col("_mx_c1")) & (F.col("_mx_b2") == F.col("_mx_c2"))
    below = (F.col("_mx_b1") < F.col("_mx_c1")) | ((F.col("_mx_b1") == F.col("_mx_c1")) & (F.col("_mx_b2") < F.col("_mx_c2")))
    plain = full.filter(~edge).withColumn("_mx_more", F.when(known & below, 1).otherwise(0))
    order = Window.partitionBy("source").orderBy("_mx_t", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    last = full.filter(edge).withColumn("_mx_upto", F.col("_mx_c2_before") + F.sum("size").over(order))
    start = upto - F.col("size")
    near = (upto <= extra) | ((start < extra) & (upto - extra < extra - start))
    last = last.withColumn("_mx_more", F.when(near, 1).otherwise(0)).drop("_mx_upto")
    out = plain.unionByName(last).withColumn(TIMES, F.col("_mx_copies") + F.col("_mx_more"))
    inner = ("mean", "copies", "part", "extra", "t", "b1", "b2", "c1", "c1_before", "c2", "c2_before", "more", "stop")
    return out.withColumn("taken", F.col("size") * F.col(TIMES)).drop(*[f"_mx_{c}" for c in inner])


def repeated(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: every row of docs as often as it is taken."""
    mixed = mix(docs.select("doc_id", "source", "text", F.struct(*docs.columns).alias("_mx_row")), **options)
    copy = F.explode(F.array_repeat(F.lit(1), F.col(TIMES).cast("int"))).alias("_mx_copy")
    return mixed.filter(F.col(TIMES) > 0).select("_mx_row.*", copy).drop("_mx_copy")


SQL = r"""
WITH sized AS (
  SELECT doc_id, source,
         coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint AS size,
         (('0x' || substr(md5('42:' || coalesce(doc_id::varchar, 'null')), 1, 13))::bigint + 0.5::double) / 4503599627370496.0::double AS u
  FROM documents),
named AS (
  SELECT source, sum(size)::bigint AS source_size, sum(size)::double / count(*) AS mean, row_number() OVER (ORDER BY source ASC NULLS LAST) - 1 AS n
  FROM sized GROUP BY source),
weighed AS (
  SELECT *, ([5.0, 2.0, 1.0])[n % 3 + 1]::double AS weight, source_size * 2.0::double AS cap FROM named),
levels AS (
  SELECT *, (sum(source_size) OVER () * 1.5::double
             - (sum(cap) OVER (ORDER BY cap / weight, n ROWS UNBOUNDED PRECEDING) - cap))
            / sum(weight) OVER (ORDER BY cap / weight, n ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM weighed),
aimed AS (
  SELECT source, source_size, mean, least(cap, weight * max(level) OVER ()) AS target FROM levels),
shared AS (
  SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END AS copies,
         CASE WHEN source_size > 0 THEN target / source_size - floor(target / source_size) ELSE 0 END AS part
  FROM aimed),
ranked AS (
  SELECT s.*, g.source_size, g.target, g.copies, g.part, g.target - g.copies * g.source_size AS extra,
         CASE WHEN g.part > 0 AND s.size > 0 THEN (s.u / (1 - s.u)) / (g.part / (1 - g.part) * (s.size / g.mean)) END AS q
  FROM sized s JOIN shared g ON s.source IS NOT DISTINCT FROM g.source),
summed AS (
  SELECT *, sum(size) OVER (PARTITION BY source ORDER BY q / (1 + q), doc_id NULLS FIRST, size ROWS UNBOUNDED PRECEDING) AS upto FROM ranked)
SELECT doc_id, size, source_size, target,
       (size * (copies + CASE WHEN part > 0 AND (upto <= extra
         OR (upto - size < extra AND upto - extra < extra - (upto - size))) THEN 1 ELSE 0 END))::bigint AS taken
FROM summed
"""
