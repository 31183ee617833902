"""The communication graph and the gain of giving a role to a site.

Edges are parcels with a weight. A relabeling replaces receivers only. The gain of (role x, site y) is what the role's
incoming parcels cost at its own site less what they cost at y; gains add up over a relabeling to exactly the drop in
total cost. For the volume cost it is V(y, x) - V(x, x): one lookup, and only pairs that share a parcel need a row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relayout.plans.cost import Cost, VolumeCost


def comm_graph(parcels: DataFrame, cost: Cost | None = None) -> DataFrame:
    """(src, dst, vol, n_pieces, weight) of the non-empty parcels."""
    return (cost or VolumeCost()).weight(parcels.filter("n_pieces > 0")).select("src", "dst", "vol", "n_pieces", "weight")


def left_neighbours(graph: DataFrame) -> DataFrame:
    """(dst, senders): who sends to each receiver."""
    return graph.groupBy("dst").agg(F.sort_array(F.collect_set("src")).alias("senders"))


def right_neighbours(graph: DataFrame) -> DataFrame:
    return graph.groupBy("src").agg(F.sort_array(F.collect_set("dst")).alias("receivers"))


def total_cost(graph: DataFrame) -> DataFrame:
    return graph.agg(F.coalesce(F.sum("weight"), F.lit(0)).alias("total"))


def relabel_graph(parcels: DataFrame, sigma: DataFrame) -> DataFrame:
    """Parcels with each receiver's role played by its site; sigma: (role, site). A missing role keeps its site."""
    moved = parcels.join(F.broadcast(sigma), F.col("dst") == F.col("role"), "left")
    return moved.withColumn("dst", F.coalesce("site", "dst").cast("int")).drop("role", "site")


def identity(spark, n: int) -> DataFrame:  # noqa: ANN001
    x = F.col("id").cast("int")
    return spark.range(n).select(x.alias("role"), x.alias("site"))


def gain_matrix(parcels: DataFrame, cost: Cost, n: int) -> DataFrame:
    """(role, site, gain) of all n * n pairs under any cost. Each parcel is priced at every site; prices are summed by
    (role, site) before they move."""
    sites = parcels.sparkSession.range(n).select(F.col("id").cast("int").alias("site"))
    priced = cost.weight(parcels.filter("n_pieces > 0").crossJoin(F.broadcast(sites)), "src", "site", "price")
    k = priced.groupBy(F.col("dst").alias("role"), "site").agg(F.sum("price").alias("price"))
    own = k.filter("role = site").select(F.col("role").alias("r"), F.col("price").alias("own"))
    found = k.join(own, F.col("role") == F.col("r")).select("role", "site", (F.col("own") - F.col("price")).alias("gain"))
    # a role that receives nothing gains nothing anywhere
    pairs = sites.withColumnRenamed("site", "role").crossJoin(sites)
    return pairs.join(found, ["role", "site"], "left").select("role", "site", F.coalesce("gain", F.lit(0)).alias("gain"))


def gain_matrix_volume(parcels: DataFrame) -> DataFrame:
    """(role, site, gain) for the volume cost, only for pairs with a parcel; any other pair gains minus the diagonal."""
    v = parcels.filter("n_pieces > 0").select(F.col("dst").alias("role"), F.col("src").alias("site"), "vol")
    own = v.filter("role = site").select(F.col("role").alias("r"), F.col("vol").alias("own"))
    gain = F.col("vol") - F.coalesce("own", F.lit(0))
    return v.join(own, F.col("role") == F.col("r"), "left").select("role", "site", gain.cast("long").alias("gain"))


def total_gain(delta: DataFrame, sigma: DataFrame) -> DataFrame:
    return delta.join(F.broadcast(sigma), ["role", "site"]).agg(F.coalesce(F.sum("gain"), F.lit(0)).alias("total_gain"))


def to_min(delta: DataFrame, how: str = "negate") -> DataFrame:
    """The same problem as a minimisation: negated, or shifted to non-negative costs."""
    if how == "negate":
        return delta.select("role", "site", (-F.col("gain")).alias("cost"))
    top: Column = F.max("gain").alias("top")
    return delta.crossJoin(F.broadcast(delta.agg(top))).select("role", "site", (F.col("top") - F.col("gain")).alias("cost"))
