"""Accuracy measures. Precision, recall and F1 are micro averages without ``none`` unless told otherwise."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.labels import NONE, split_label
from ..ontology import LABELS


def _count(c: Column) -> Column:
    return F.sum(F.when(c, 1).otherwise(0)).cast("long")


def accuracy_prf(preds: DataFrame, by: tuple[str, ...] = ("method",), invalid: str = "wrong") -> DataFrame:
    """acc, p, r, f1 of each method. A prediction outside the label set is wrong; with ``invalid="none"`` it reads as none."""
    known = F.col("pred").isin(LABELS)
    pred = F.when(known, F.col("pred")) if invalid == "wrong" else F.when(known, F.col("pred")).otherwise(NONE)
    p = preds.withColumn("_p", pred)
    right = F.col("_p").eqNullSafe(F.col("gold"))
    sums = p.groupBy(*by).agg(
        F.count("*").alias("n"), _count(right).alias("right"), _count(right & (F.col("gold") != NONE)).alias("tp"),
        _count(F.col("_p") != NONE).alias("said"), _count(F.col("gold") != NONE).alias("real"),
    )
    prec, rec = F.try_divide(F.col("tp"), F.col("said")), F.try_divide(F.col("tp"), F.col("real"))
    f1 = F.coalesce(F.try_divide(2 * prec * rec, prec + rec), F.lit(0.0))
    zero = F.lit(0.0)
    return sums.select(*by, F.round(F.col("right") / F.col("n"), 6).alias("acc"), F.round(F.coalesce(prec, zero), 6).alias("p"), F.round(F.coalesce(rec, zero), 6).alias("r"), F.round(f1, 6).alias("f1"))


def confusion(preds: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    return preds.groupBy(*by, "gold", "pred").agg(F.count("*").alias("n"))


def per_class(preds: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """label, support, predicted, tp, p, r, f1: one scan, two rows out of each (as gold and as prediction)."""
    both = preds.select(*by, F.explode(F.array(F.struct(F.col("gold").alias("label"), F.lit(1).alias("g"), F.lit(0).alias("s"), (F.col("gold") == F.col("pred")).cast("int").alias("t")), F.struct(F.col("pred").alias("label"), F.lit(0).alias("g"), F.lit(1).alias("s"), F.lit(0).alias("t")))).alias("x"))
    sums = both.groupBy(*by, F.col("x.label").alias("label")).agg(F.sum("x.g").cast("long").alias("support"), F.sum("x.s").cast("long").alias("predicted"), F.coalesce(F.sum("x.t"), F.lit(0)).cast("long").alias("tp"))
    p, r = F.coalesce(F.try_divide(F.col("tp"), F.col("predicted")), F.lit(0.0)), F.coalesce(F.try_divide(F.col("tp"), F.col("support")), F.lit(0.0))
    return sums.select(*by, "label", "support", "predicted", "tp", F.round(p, 6).alias("p"), F.round(r, 6).alias("r"), F.round(F.coalesce(F.try_divide(2 * p * r, p + r), F.lit(0.0)), 6).alias("f1"))


def averaged_prf(preds: DataFrame, average: str, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """micro, macro or weighted over all labels, none among them."""
    if average == "micro":
        acc = preds.groupBy(*by).agg(F.round(F.avg(F.col("gold").eqNullSafe(F.col("pred")).cast("double")), 6).alias("p"))
        return acc.select(*by, "p", F.col("p").alias("r"), F.col("p").alias("f1"))
    each = per_class(preds, by).where("support > 0")
    if average == "macro":
        return each.groupBy(*by).agg(*[F.round(F.avg(c), 5).alias(c) for c in ("p", "r", "f1")])
    if average == "weighted":
        return each.groupBy(*by).agg(*[F.round(F.sum(F.col(c) * F.col("support")) / F.sum("support"), 5).alias(c) for c in ("p", "r", "f1")])
    raise ValueError("average is micro, macro or weighted")


def top_confusions(preds: DataFrame, k: int = 10, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """The k most frequent mistakes of each method."""
    wrong = confusion(preds.where("gold <> pred"), by)
    order = W.partitionBy(*by).orderBy(F.desc("n"), "gold", "pred")
    return wrong.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k)


def none_discrimination(preds: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """How well real relations are told from none, whichever relation it is, and how often a relation is said where there is none."""
    g, p = F.col("gold") != NONE, F.col("pred") != NONE
    s = preds.groupBy(*by).agg(_count(g & p).alias("tp"), _count(~g & p).alias("fp"), _count(g & ~p).alias("fn"), _count(~g & ~p).alias("tn"))
    return s.select(*by, "tp", "fp", "fn", "tn", F.round(F.try_divide(F.col("fp"), F.col("fp") + F.col("tn")), 6).alias("over_rate"), F.round((F.col("tp") + F.col("tn")) / (F.col("tp") + F.col("fp") + F.col("fn") + F.col("tn")), 6).alias("binary_acc"))


def type_accuracy(preds: DataFrame, by: tuple[str, ...] = ("method",)) -> DataFrame:
    """Among real relations that were answered with one: how often the object type, the entity type and both are right."""
    real = preds.where((F.col("gold") != NONE) & (F.col("pred") != NONE)).select(*by, split_label(F.col("gold")).alias("g"), split_label(F.col("pred")).alias("p"))
    o, e = F.col("g.obj_type").eqNullSafe(F.col("p.obj_type")), F.col("g.ent_type").eqNullSafe(F.col("p.ent_type"))
    return real.groupBy(*by).agg(F.count("*").alias("n"), *[F.round(F.avg(c.cast("double")), 6).alias(a) for c, a in ((o, "obj_acc"), (e, "ent_acc"), (o & e, "both_acc"))])


def relative_gain(metrics: DataFrame, method: str, base: str) -> DataFrame:
    """metric, gain: the ratio of the two methods' values less 1."""
    long = metrics.unpivot(["method"], ["acc", "p", "r", "f1"], "metric", "value")
    two = long.where(F.col("method").isin(method, base)).groupBy("metric").agg(F.max(F.when(F.col("method") == method, F.col("value"))).alias("a"), F.max(F.when(F.col("method") == base, F.col("value"))).alias("b"))
    return two.select("metric", F.round(F.try_divide(F.col("a"), F.col("b")) - 1, 6).alias("gain"))


def rank_methods(metrics: DataFrame) -> DataFrame:
    """method, metric, value, place: 1 is best, 2 the runner-up."""
    long = metrics.unpivot(["method"], ["acc", "p", "r", "f1"], "metric", "value")
    return long.withColumn("place", F.dense_rank().over(W.partitionBy("metric").orderBy(F.desc("value"))).cast("long"))


def case_study(preds: DataFrame, methods: list[str]) -> DataFrame:
    """Samples that only the last of the methods gets right, with what each said and whether its types were right."""
    wide = preds.where(F.col("method").isin(methods)).groupBy("sample_id", "gold").pivot("method", methods).agg(F.first("pred"))
    only = F.col(methods[-1]) == F.col("gold")
    for m in methods[:-1]:
        only = only & (F.col(m) != F.col("gold"))
    g = split_label(F.col("gold"))
    said = [x for m in methods for x in (F.col(m).alias(f"said_{m}"), (split_label(F.col(m))["obj_type"].eqNullSafe(g["obj_type"]) & split_label(F.col(m))["ent_type"].eqNullSafe(g["ent_type"])).alias(f"types_{m}"))]
    return wide.where(only).select("sample_id", "gold", *said)


def to_edges(samples: DataFrame, preds: DataFrame) -> DataFrame:
    """Graph edges: image object, relation, entity, and how often it was predicted."""
    both = preds.where(F.col("pred") != NONE).join(samples.select("sample_id", "vec_id", "entity"), "sample_id")
    return both.groupBy(F.col("vec_id").alias("head"), split_label(F.col("pred"))["relation"].alias("relation"), F.col("entity").alias("tail")).agg(F.count("*").alias("n"))


def lookup(edges: DataFrame, relation: str, entity: str | None = None) -> DataFrame:
    hits = edges.where(F.col("relation") == relation)
    return hits if entity is None else hits.where(F.col("tail") == entity)
