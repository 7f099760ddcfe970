"""Mixing sources to target weights by entropy balancing, in DataFrame operations only.

Document rates r are the ones nearest to 1 in relative entropy (each document weighed by its size) among those that meet
the token constraints sum(size * x_k * r) = target_k. They have the form r = exp(sum_k lambda_k x_k). The convex dual

    sum(size * exp(lambda . x)) - lambda . target

is solved by Newton iterations. Where every document meets one constraint only (its source), gradient and Hessian are
diagonal and both are sums per source: the documents are aggregated once and all sources iterate together, each in its own
row (:func:`source_rates`). For overlapping features, :func:`tilt` makes one distributed pass per iteration that returns
the gradient and the Hessian, k + k^2 numbers whatever the data.

Rates become copies: every document gets floor(r); the rest of a source's target goes, one more copy each, to its
documents in the order of a hash of doc_id, until the words are spent. Hash order is cut into BUCKETS slices that are
summed first; only the one slice of a source in which the words run out is put in order. Then each source changes the
one document whose size comes nearest to the words still missing or spent too many. What comes out is a rule a source
(:func:`rules`): copies follow from a document's own id and size and its source's rule, so documents are mixed in place.

Null and empty texts have size 0: they spend no words and get no extra copy. A null source is a source of its own, last
in order. Repeated rows are separate documents with the same number of copies: rows that tie in the order all have the
extra copy or none. An empty table gives an empty result. Only doc_id, text and source are read; other columns pass.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ctxloom.session import load, materialise

BUCKETS = 4096
ITERATIONS = 60
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (3, 1, 2), share: float = 1.5, most: float = 2.0) -> DataFrame:
    """source, source_size, target per source: ``share`` of all words by weight, no source above ``most`` times its size.

    Sources fill in the order of most * size / weight; once a source is full, what it could not take goes to the others by
    weight, so the level at each source is what is left over the weight that is left. One row per source throughout.
    """
    per = sizes.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"))
    w = F.element_at(F.array(*map(F.lit, weights)), ((F.col("nth") - 1) % len(weights) + 1).cast("int"))
    per = per.withColumn("nth", F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last()))).withColumn("weight", w.cast("double"))
    filling = Window.orderBy(F.col("source_size") / F.col("weight"), "nth")
    before = filling.rowsBetween(Window.unboundedPreceding, -1)
    total, weight = F.sum("source_size").over(Window.partitionBy()), F.sum("weight").over(Window.partitionBy())
    full_before = F.coalesce(F.sum("source_size").over(before), F.lit(0)) * most
    weight_left = weight - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    per = per.withColumn("level", (total * share - full_before) / weight_left)
    per = per.withColumn("full", F.col("level") * F.col("weight") > F.col("source_size") * most)
    # the first source in filling order that stays below its limit sets the level of all after it
    level = F.min(F.when(~F.col("full"), F.struct(F.col("source_size") / F.col("weight"), "nth", "level"))).over(Window.partitionBy())
    target = F.least(F.col("source_size") * most, F.coalesce(level["level"], F.lit(float("inf"))) * F.col("weight"))
    return per.select("source", "source_size", F.round(target, 6).alias("target"))


def source_rates(targets: DataFrame) -> DataFrame:
    """Adds lambda and rate = exp(lambda) per source, by Newton steps on the dual, all sources at once."""

    def step(lam: Column, _: Column) -> Column:
        value = F.col("source_size") * F.exp(lam)
        return lam - F.greatest((value - F.col("target")) / value, F.lit(-1.0))

    solved = F.aggregate(F.sequence(F.lit(1), F.lit(ITERATIONS)), F.lit(0.0), step)
    usable = (F.col("source_size") > 0) & (F.col("target") > 0)
    return targets.withColumn("lambda", F.when(usable, solved)).withColumn("rate", F.coalesce(F.exp("lambda"), F.lit(0.0)))


def tilt(rows: DataFrame, features: list[str], targets: list[float], size: str = "size", rounds: int = 50, tol: float = 1e-9) -> np.ndarray:
    """lambda for any numeric feature columns (few: k). One aggregation a round brings k + k^2 sums to the driver."""
    k = len(features)
    lam = np.zeros(k)
    goal = np.asarray(targets, float)
    x = [F.col(f).cast("double") for f in features]

    def objective(at: np.ndarray) -> Column:
        return F.col(size) * F.exp(sum((F.lit(float(v)) * c for v, c in zip(at, x)), F.lit(0.0)))

    for _ in range(rounds):
        mass = objective(lam)
        sums = [F.sum(mass * c) for c in x] + [F.sum(mass * a * b) for a in x for b in x]
        got = np.array(rows.agg(*[s.alias(f"s{i}") for i, s in enumerate(sums)]).first(), float)
        grad, hess = got[:k] - goal, got[k:].reshape(k, k)
        if np.abs(grad).max() <= tol * max(1.0, np.abs(goal).max()):
            break
        step = np.linalg.lstsq(hess, grad, rcond=None)[0]
        tries = [lam - step * 0.5**i for i in range(12)]
        # one pass values all step lengths of the line search
        values = rows.agg(*[F.sum(objective(t)).alias(f"v{i}") for i, t in enumerate([lam, *tries])]).first()
        scores = [v - float(t @ goal) for v, t in zip(values, [lam, *tries])]
        best = int(np.argmin(scores[1:]))
        if scores[1 + best] >= scores[0]:
            break
        lam = tries[best]
    return lam


def hash_order(doc_id: Column) -> Column:
    """Position of a document in its source's order: 52 bits of a digest that SQL engines share."""
    return F.conv(F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), 1, 13), 16, 10).cast("long")


def _keyed(rows: DataFrame) -> DataFrame:
    """Adds key, the place in the source's order with its ties, and bucket, the slice of the order."""
    place = hash_order(F.col("doc_id"))
    return rows.withColumn("key", F.struct(place.alias("place"), F.col("doc_id").alias("id"), F.col("size").alias("words"))).withColumn("bucket", F.expr(f"int(key.place div {2**52 // BUCKETS})"))


def _extra() -> Column:
    """1 if the rule's words still paid for one more copy of the document."""
    paid = (F.col("bucket") < F.col("cut_bucket")) | ((F.col("bucket") == F.col("cut_bucket")) & F.col("cut_key").isNotNull() & (F.col("key") <= F.col("cut_key")))
    return ((F.col("size") > 0) & paid).cast("int")


def _with_rule(rows: DataFrame, table: DataFrame) -> DataFrame:
    """Rows with their source's rule. A row a source: the planner sends it out if it is small, or sorts and merges."""
    named = table.withColumnRenamed("source", "_source")
    return rows.join(named, rows["source"].eqNullSafe(named["_source"])).drop("_source")


def rules(sizes: DataFrame, rates: DataFrame) -> DataFrame:
    """source, source_size, target, whole, cut_bucket, cut_key, flip_key per source.

    A document gets ``whole`` copies, and one more up to ``cut_key`` in its source's order, as far as all of it fits into
    what the target still pays: a source's words then miss the target by less than a document. The document at
    ``flip_key`` gains or loses its extra copy, where that comes nearer (ties: the first in order).
    """
    rows = _keyed(sizes)
    per = rates.withColumn("rate", F.round("rate", 9)).select("source", "source_size", "target", F.floor("rate").alias("whole"), F.round(F.col("target") - F.floor("rate") * F.col("source_size"), 6).alias("rest"))
    before = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    summed = rows.groupBy("source", "bucket").agg(F.sum("size").alias("bucket_size")).withColumn("ahead", F.coalesce(F.sum("bucket_size").over(before), F.lit(0)))
    over = F.min(F.when(F.col("ahead") + F.col("bucket_size") > F.col("rest"), F.struct("bucket", "ahead")))
    table = _with_rule(summed, per).groupBy("source", "source_size", "target", "whole", "rest").agg(over.alias("o"))
    table = materialise(table.select("source", "source_size", "target", "whole", "rest", F.coalesce("o.bucket", F.lit(BUCKETS)).alias("cut_bucket"), F.col("o.ahead").alias("ahead")), "rules")
    order = Window.partitionBy("source").orderBy("key").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    last = _with_rule(rows, table).where("bucket = cut_bucket").withColumn("spent", F.col("ahead") + F.sum("size").over(order)).where("spent <= rest").groupBy("source").agg(F.max("key").alias("cut_key"))
    table = table.join(last.withColumnRenamed("source", "_source"), F.col("source").eqNullSafe(F.col("_source")), "left").drop("_source")
    table = materialise(table, "rules")
    marked = _with_rule(rows, table).withColumn("extra", _extra())
    missing = marked.groupBy("source").agg((F.max("rest") - F.sum(F.col("size") * F.col("extra"))).alias("missing"))
    after = F.col("missing") - F.col("size") * (1 - 2 * F.col("extra"))
    flip = F.min(F.struct(F.round(F.abs(after), 6).alias("left"), "key")).alias("flip")
    best = _with_rule(marked, materialise(missing, "rules")).where(F.abs(after) < F.abs("missing")).groupBy("source").agg(flip).select(F.col("source").alias("_source"), F.col("flip.key").alias("flip_key"))
    return materialise(table.join(best, F.col("source").eqNullSafe(F.col("_source")), "left").drop("_source", "rest", "ahead"), "rules")


def mix(rows: DataFrame, table: DataFrame) -> DataFrame:
    """Adds source_size, target and copies to rows with doc_id, source and size, by the sources' rules."""
    kept = [c for c in rows.columns if c not in ("source_size", "target", "copies")]
    marked = _with_rule(_keyed(rows.select(*kept)), table)
    flipped = F.coalesce(F.col("key") == F.col("flip_key"), F.lit(False))
    extra = F.when(flipped, 1 - _extra()).otherwise(_extra())
    return marked.withColumn("copies", (F.col("whole") + extra).cast("int")).select(*kept, "source_size", "target", "copies")


def sized(docs: DataFrame) -> DataFrame:
    return materialise(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")), "sizes")


def mix_documents(docs: DataFrame) -> DataFrame:
    """doc_id, source, size, source_size, target, copies for all documents."""
    sizes = sized(docs)
    return mix(sizes, rules(sizes, source_rates(source_targets(sizes))))


def repeated(docs: DataFrame) -> DataFrame:
    """The documents themselves, each as often as the mix takes it: never, once or twice. Texts stay where they are."""
    sizes = sized(docs)
    table = rules(sizes, source_rates(source_targets(sizes)))
    names = {c: f"_own_{i}" for i, c in enumerate(docs.columns)}
    rows = docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), *[F.col(c).alias(n) for c, n in names.items()])
    taken = mix(rows, table).where("copies > 0")
    return taken.select(*[F.col(n).alias(c) for c, n in names.items()], F.explode(F.sequence(F.lit(1), F.col("copies"))).alias("_copy")).drop("_copy")


def op6_entropy_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_documents(load(spark, sf_dir, "documents")).select(
        "doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).cast("long").alias("taken")
    )


ORACLE = r"""
WITH d AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size,
         ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 13))::BIGINT AS place
  FROM documents),
p AS (SELECT source, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY source NULLS LAST) AS nth FROM d GROUP BY source),
w AS (SELECT *, [3.0, 1.0, 2.0][(nth - 1) % 3 + 1]::DOUBLE AS weight FROM p),
f AS (SELECT *, (sum(source_size) OVER () * 1.5
        - coalesce(sum(source_size) OVER (ORDER BY source_size / weight, nth ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) * 2.0)
        / (sum(weight) OVER () - coalesce(sum(weight) OVER (ORDER BY source_size / weight, nth ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS level
      FROM w),
l AS (SELECT level FROM f WHERE level * weight <= source_size * 2.0 ORDER BY source_size / weight, nth LIMIT 1),
t AS (SELECT source, source_size, round(least(source_size * 2.0, coalesce((SELECT level FROM l), 'inf'::DOUBLE) * weight), 6) AS target FROM f),
r AS (SELECT *, CASE WHEN source_size > 0 THEN floor(round(target / source_size, 9)) ELSE 0 END AS whole FROM t),
c AS (SELECT d.doc_id, d.source, d.size, d.place, r.source_size, r.target, r.whole, round(r.target - r.whole * r.source_size, 6) AS rest,
        coalesce(sum(d.size) OVER (PARTITION BY d.source ORDER BY place, d.doc_id, d.size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead
      FROM d JOIN r ON d.source IS NOT DISTINCT FROM r.source),
e AS (SELECT *, CASE WHEN ahead + size <= rest THEN 1 ELSE 0 END AS extra FROM c),
m AS (SELECT *, rest - sum(size * extra) OVER (PARTITION BY source) AS missing FROM e),
b AS (SELECT source, doc_id FROM m WHERE abs(missing - size * (1 - 2 * extra)) < abs(missing)
      QUALIFY row_number() OVER (PARTITION BY source ORDER BY round(abs(missing - size * (1 - 2 * extra)), 6), place, doc_id, size) = 1)
SELECT e.doc_id, e.size, e.source_size, e.target,
       (e.size * (e.whole + CASE WHEN b.doc_id IS NULL THEN e.extra ELSE 1 - e.extra END))::BIGINT AS taken
FROM e LEFT JOIN b ON e.doc_id = b.doc_id
"""

QUERIES = {"op6_entropy_mixing": op6_entropy_mixing}
ORACLES = {"op6_entropy_mixing": ORACLE}
