"""True and false positives and the rates made of them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _near(findings: DataFrame, truth: DataFrame, tol: int) -> Column:
    return (findings["unit_id"] == truth["unit_id"]) & (findings["category"] == truth["category"]) & (F.abs(findings["line"] - truth["line"]) <= tol)


def tp(findings: DataFrame, truth: DataFrame, tol: int = 0) -> DataFrame:
    """Labels that a finding of their category hits at their line."""
    return truth.join(findings, _near(findings, truth, tol), "left_semi")


def fn(findings: DataFrame, truth: DataFrame, tol: int = 0) -> DataFrame:
    return truth.join(findings, _near(findings, truth, tol), "left_anti")


def fp(findings: DataFrame, truth: DataFrame, restrict: bool = True, tol: int = 0) -> DataFrame:
    """Findings off any label, repeats counted again; ``restrict`` looks only at units labelled with the finding's category."""
    wrong = findings.join(truth, _near(findings, truth, tol), "left_anti")
    if not restrict:
        return wrong
    sets = truth.select("unit_id", "category").distinct()
    return wrong.join(sets, ["unit_id", "category"], "left_semi")


def once(findings: DataFrame) -> DataFrame:
    """One finding of each rule at each line of a unit, the repeated reports left out."""
    return findings.dropDuplicates(["unit_id", "rule_id", "line"])


def mismatch(findings: DataFrame, truth: DataFrame, tol: int = 0) -> DataFrame:
    """Findings in a unit labelled with their category, but at another line."""
    return fp(findings, truth, True, tol)


def rates(df: DataFrame) -> DataFrame:
    """Precision, recall and F1 beside columns ``tp, fp, labels``; null where nothing was found or labelled."""
    prec = F.try_divide(F.col("tp").cast("double"), F.col("tp") + F.col("fp"))
    rec = F.try_divide(F.col("tp").cast("double"), F.col("labels"))
    f1 = F.try_divide(2 * prec * rec, prec + rec)
    return df.withColumns({"prec": F.round(prec, 6), "rec": F.round(rec, 6), "f1": F.round(f1, 6)})


def by_category(findings: DataFrame, truth: DataFrame, restrict: bool = True, tol: int = 0) -> DataFrame:
    """labels, tp, fp and rates per category, and a total."""
    one = lambda d, n: d.groupBy("category").agg(F.count("*").alias(n))
    all_ = one(truth, "labels").join(one(tp(findings, truth, tol), "tp"), "category", "full").join(one(fp(findings, truth, restrict, tol), "fp"), "category", "full")
    all_ = all_.na.fill(0, ["labels", "tp", "fp"])
    total = all_.groupBy(F.lit("total").alias("category")).agg(*(F.sum(c).alias(c) for c in ("labels", "tp", "fp")))
    return rates(all_.unionByName(total))


def coverage(df: DataFrame) -> DataFrame:
    """Of ``tool, category, tp``: categories with a hit, hits, and the rank by hits."""
    from pyspark.sql import Window

    out = df.where("category <> 'total'").groupBy("tool").agg(F.count_if(F.col("tp") > 0).alias("categories"), F.sum("tp").alias("tp"))
    return out.withColumn("place", F.rank().over(Window.orderBy(F.desc("tp"))))


def class_pairs(matches: DataFrame, classes: DataFrame) -> DataFrame:
    """``pairs`` (ordered) from matches between groups of equal rows: ``classes`` has id (of the group), class and ``n``, the rows.

    A match of a group with itself stands for the pairs of its different rows.
    """
    a = classes.select(F.col("id").alias("query_id"), "class", "n")
    b = classes.select(F.col("id").alias("target_id"), F.col("class").alias("other"), F.col("n").alias("m"))
    same, times = F.col("class") == F.col("other"), F.col("n") * F.col("m")
    own = F.when(same & (F.col("query_id") == F.col("target_id")), F.col("n")).otherwise(0)
    found = matches.join(a, "query_id").join(b, "target_id").groupBy("class").agg(F.sum(F.when(same, times - own).otherwise(0)).alias("tp"), F.sum(F.when(~same, times).otherwise(0)).alias("fp"))
    c = F.col("c")
    total = classes.groupBy("class").agg(F.sum("n").alias("c")).select("class", (c * (c - 1)).alias("labels"))
    return rates(total.join(found, "class", "left").na.fill(0, ["tp", "fp"]))


def pairs(matches: DataFrame, classes: DataFrame, ordered: bool = True) -> DataFrame:
    """Per class of the query: pairs over the threshold in the same and in another class, and recall in the chosen universe.

    ``matches`` has query_id, target_id; ``classes`` id, class. Unordered: a pair counts once, in either direction.
    """
    if not ordered:
        matches = matches.select(F.least("query_id", "target_id").alias("query_id"), F.greatest("query_id", "target_id").alias("target_id")).distinct()
    a = classes.select(F.col("id").alias("query_id"), F.col("class"))
    b = classes.select(F.col("id").alias("target_id"), F.col("class").alias("other"))
    found = matches.join(a, "query_id").join(b, "target_id").groupBy("class").agg(F.count_if(F.col("class") == F.col("other")).alias("tp"), F.count_if(F.col("class") != F.col("other")).alias("fp"))
    c = F.col("c")
    same = classes.groupBy("class").agg(F.count("*").alias("c")).select("class", (c * (c - 1) if ordered else (c * (c - 1) / 2).cast("long")).alias("labels"))
    return rates(same.join(found, "class", "left").na.fill(0, ["tp", "fp"]))
