"""Points to atomic regions: the nearest of given centres, or clusters of the points themselves."""
from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MAX_CENTRES = 4096


def squared_distance(a: Column, b: Column) -> Column:
    d = F.zip_with(a, b, lambda x, y: (x.cast("double") - y.cast("double")) * (x.cast("double") - y.cast("double")))
    return F.aggregate(d, F.lit(0.0), lambda s, x: s + x)


def centres(points: DataFrame, label: str, vector: str, digits: int = 6) -> DataFrame:
    """r, centre: the mean vector of each label, rounded so that the order of summing does not show."""
    rows = points.where(F.col(label).isNotNull() & F.col(vector).isNotNull()).select(F.col(label).alias("r"), F.posexplode(vector).alias("at", "x"))
    mean = rows.groupBy("r", "at").agg(F.round(F.avg(F.col("x").cast("double")), digits).alias("x"))
    return mean.groupBy("r").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "x"))), lambda s: s["x"]).alias("centre"))


def nearest(points: DataFrame, at: DataFrame, key: str, vector: str, digits: int = 6) -> DataFrame:
    """key, r: the nearest centre of each point, ties (to so many digits) to the smaller r. One pass over the points: the
    centres, MAX_CENTRES at most (checked), go along as one array."""
    if (n := at.limit(MAX_CENTRES + 1).count()) > MAX_CENTRES or not n:
        raise ValueError(f"{n} centres; between 1 and {MAX_CENTRES} are possible")
    all_ = at.agg(F.array_sort(F.collect_list(F.struct("r", "centre"))).alias("all"))
    rows = points.where(F.col(vector).isNotNull()).join(F.broadcast(all_), F.lit(True))
    best = F.array_min(F.transform("all", lambda c: F.struct(F.round(squared_distance(F.col(vector), c["centre"]), digits).alias("d"), c["r"].alias("r"))))
    return rows.select(key, best["r"].alias("r"))


def cluster(points: DataFrame, key: str, vector: str, k: int, seed: int = 1, rounds: int = 20) -> DataFrame:
    """key, r: k-means clusters as regions, numbered from 0."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    rows = points.where(F.col(vector).isNotNull()).select(key, array_to_vector(F.col(vector).cast("array<double>")).alias("features"))
    model = KMeans(k=k, seed=seed, maxIter=rounds).fit(rows)
    return model.transform(rows).select(key, F.col("prediction").cast("int").alias("r"))
