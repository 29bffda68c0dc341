"""Grid over N-gram length, share and score: each pair is scored once, queries of few letters against all targets in one pass."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codeprov.clone import levels
from codeprov.clone.match import scored
from codeprov.measure.confusion import rates
from codeprov.session import cut_lineage


def sweep(queries: DataFrame, targets: DataFrame, truth: DataFrame, ns: list[int], etas: list[float], epss: list[float], strategy: str = "auto") -> DataFrame:
    """``n, eta, eps, tp, fp, fn, prec, rec, f1``; ``truth`` has query_id, target_id."""
    known = cut_lineage(truth.select("query_id", "target_id").distinct().withColumn("hit", F.lit(1)))
    small = (queries.agg(F.sum(F.length(F.array_join("subs", ".")))).first()[0] or 0) <= levels.MOST_ASKED
    one = _by_levels if strategy == "auto" and small else _by_scores
    counts = one(queries, targets, known, ns, etas, epss, strategy)
    total = known.agg(F.count("*").alias("labels"))
    out = rates(counts.join(F.broadcast(total)))
    return out.select(F.col("n").cast("long").alias("n"), "eta", "eps", "tp", "fp", (F.col("labels") - F.col("tp")).alias("fn"), "prec", "rec", "f1")


def _grid(spark, ns, etas, epss) -> DataFrame:
    rows = [(n, float(eta), float(eps)) for n in ns for eta in etas for eps in epss]
    return spark.createDataFrame([(k, *r) for k, r in enumerate(rows)], "cell int, n int, eta double, eps double")


def _by_levels(queries, targets, known, ns, etas, epss, strategy) -> DataFrame:
    """Counts of pairs by the cells that they reach, in one pass over the targets."""
    found = levels.reached(queries, targets, ns, etas, epss).join(known, ["query_id", "target_id"], "left")
    one = found.select(F.explode("cells").alias("cell"), "hit").groupBy("cell").agg(F.count("hit").alias("tp"), F.count_if(F.col("hit").isNull()).alias("fp"))
    return _grid(queries.sparkSession, ns, etas, epss).join(F.broadcast(one), "cell", "left").na.fill(0, ["tp", "fp"]).drop("cell")


def _by_scores(queries, targets, known, ns, etas, epss, strategy) -> DataFrame:
    every = [scored(queries, targets, n, min(etas), strategy).select(F.lit(n).alias("n"), "query_id", "target_id", "shared", "n_grams", "score") for n in ns]
    found = reduce(DataFrame.unionByName, every).join(known, ["query_id", "target_id"], "left")
    kept = _grid(queries.sparkSession, ns, etas, epss).join(found, "n", "left").withColumn("ok", (F.col("shared") >= F.col("eta") * F.col("n_grams")) & (F.col("score") >= 100 * F.col("eps") - 1e-9))
    return kept.groupBy("n", "eta", "eps").agg(F.count_if(F.col("ok") & F.col("hit").isNotNull()).alias("tp"), F.count_if(F.col("ok") & F.col("hit").isNull()).alias("fp"))
