"""Threshold graphs over similar facets, their connected parts, and other clusterings."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def threshold_edges(sim: DataFrame, sigma: float = 0.35) -> DataFrame:
    return sim.where(F.col("sim") > sigma).select("query", "a", "b")


def components(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """``query, facet, component``: the smallest facet that each one reaches.

    A seed has a few dozen candidates at most, so its graph is one row: edges are folded into
    a map of labels, each edge giving both its parts the smaller label. Columns of ``nodes``
    besides ``facet`` name the graph.
    """
    keys = [c for c in nodes.columns if c != "facet"]
    points = nodes.groupBy(*keys).agg(F.map_from_entries(F.collect_set(F.struct(F.col("facet").alias("k"), F.col("facet").alias("v")))).alias("start"))
    lines = edges.groupBy(*keys).agg(F.collect_list(F.struct("a", "b")).alias("edges"))
    packed = points.join(lines, keys, "left").withColumn("edges", F.coalesce("edges", F.expr("cast(array() as array<struct<a:string,b:string>>)")))
    fold = "aggregate(edges, start, (acc, e) -> transform_values(acc, (k, v) -> if(v = acc[e.a] or v = acc[e.b], least(acc[e.a], acc[e.b]), v)))"
    return packed.select(*keys, F.explode(F.expr(fold)).alias("facet", "component"))


def label_clusters(clusters: DataFrame, scored: DataFrame) -> DataFrame:
    """Adds ``score, cluster_label, is_label``: the label is the member with the highest score."""
    best = W.partitionBy("query", "component").orderBy(F.col("ranked").desc(), "facet")
    x = clusters.join(scored.select("query", "facet", "score"), ["query", "facet"]).withColumn("ranked", F.round("score", 9))
    return x.withColumn("cluster_label", F.first("facet").over(best)).select("query", "facet", "component", "cluster_label", (F.col("facet") == F.col("cluster_label")).alias("is_label"), "score")


def star_cover(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """``query, facet, center``: star clustering.

    Facets are taken by falling degree; one that no earlier center covers becomes a center and
    covers its neighbours. The fold runs inside one row per seed.
    """
    both = edges.select("query", F.col("a").alias("facet"), F.col("b").alias("near")).unionByName(edges.select("query", F.col("b").alias("facet"), F.col("a").alias("near")))
    around = nodes.select("query", "facet").join(both.groupBy("query", "facet").agg(F.array_sort(F.collect_list("near")).alias("near")), ["query", "facet"], "left")
    around = around.withColumn("near", F.coalesce("near", F.array().cast("array<string>")))
    packed = around.groupBy("query").agg(F.array_sort(F.collect_list(F.struct((-F.size("near")).alias("order"), "facet", "near"))).alias("xs"))
    empty = F.expr("cast(map() as map<string,string>)")
    cover = lambda acc, x: F.when(F.map_contains_key(acc, x["facet"]), acc).otherwise(
        F.map_concat(acc, F.map_from_arrays(F.array_union(F.array(x["facet"]), F.filter(x["near"], lambda n: ~F.map_contains_key(acc, n))), F.transform(F.array_union(F.array(x["facet"]), F.filter(x["near"], lambda n: ~F.map_contains_key(acc, n))), lambda _: x["facet"])))
    )
    return packed.select("query", F.explode(F.aggregate("xs", empty, cover)).alias("facet", "center"))


def kmeans_by_query(vectors: DataFrame, k: int = 8, rounds: int = 25) -> DataFrame:
    """``query, facet, cluster`` by k-means over each seed's own unit vectors (``query, facet, term, w``).

    A seed has a few dozen facets, so its vectors fit one task. Starts are farthest points, the
    first facet by name first; nothing is random.
    """
    import numpy as np
    import pandas as pd

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        wide = rows.pivot_table(index="facet", columns="term", values="w", fill_value=0.0).sort_index()
        x = wide.to_numpy()
        centers = [x[0]]
        while len(centers) < min(k, len(x)):
            centers.append(x[np.round(np.min([((x - c) ** 2).sum(1) for c in centers], axis=0), 9).argmax()])
        centers = np.array(centers)
        for _ in range(rounds):
            own = np.round(((x[:, None, :] - centers[None]) ** 2).sum(2), 9).argmin(1)
            fresh = np.array([x[own == i].mean(0) if (own == i).any() else centers[i] for i in range(len(centers))])
            if np.allclose(fresh, centers):
                break
            centers = fresh
        return pd.DataFrame({"query": rows["query"].iloc[0], "facet": wide.index, "cluster": own.astype("int64")})

    return vectors.groupBy("query").applyInPandas(run, "query string, facet string, cluster long")


def spectral_by_query(nodes: DataFrame, sim: DataFrame, k: int = 8) -> DataFrame:
    """``query, facet, cluster``: each seed's similarity graph, by the leading vectors of its normalized matrix and k-means on them."""
    import numpy as np
    import pandas as pd

    points = nodes.select("query", F.col("facet").alias("a"), F.col("facet").alias("b"), F.lit(1.0).alias("sim"))
    rows = points.unionByName(sim.select("query", "a", "b", "sim"))

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        names = sorted(set(rows["a"]) | set(rows["b"]))
        at = {n: i for i, n in enumerate(names)}
        m = np.zeros((len(names), len(names)))
        i, j = rows["a"].map(at).to_numpy(), rows["b"].map(at).to_numpy()
        m[i, j] = m[j, i] = rows["sim"].to_numpy()
        d = 1 / np.sqrt(m.sum(1))
        _, vectors = np.linalg.eigh(m * d[:, None] * d[None, :])
        x = vectors[:, -min(k, len(names)) :]
        x = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
        centers = [x[0]]
        while len(centers) < min(k, len(x)):
            centers.append(x[np.round(np.max([x @ c for c in centers], axis=0), 9).argmin()])
        own = np.round(x @ np.array(centers).T, 9).argmax(1)
        return pd.DataFrame({"query": rows["query"].iloc[0], "facet": names, "cluster": own.astype("int64")})

    return rows.groupBy("query").applyInPandas(run, "query string, facet string, cluster long")
