"""Union of shard graphs through shared vectors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

POLICIES = ("union", "nearest", "hashed", "reprune")


def _nearest(edges: Column, degree: int) -> Column:
    return F.slice(F.array_sort(F.transform(edges, lambda e: F.struct(e["d"].alias("d"), e["id"].alias("id")))), 1, degree)


def _plain(edges: Column) -> Column:
    return F.transform(edges, lambda e: F.struct(e["id"].alias("id"), e["d"].alias("d")))


def merge_graphs(graphs: DataFrame, degree: int, policy: str = "nearest", assignment: DataFrame | None = None, vectors: DataFrame | None = None, alpha: float = 1.2, col: str = "q") -> DataFrame:
    """Rows (vec_id, nbrs, n_homes): distinct edges of a vector over its shards, cut to ``degree``.

    Vectors of one shard skip the shuffle when ``assignment`` tells their ``n_homes``; the others
    meet by id, a bounded list of at most ``max_homes`` rows each. Grouping is by id, so neither
    the order inside a shard nor that of the shards matters. Policies: ``union`` keeps all,
    ``nearest`` the closest by (d, id), ``hashed`` a seeded choice that keeps long links, and
    ``reprune`` removes occluded edges, which needs the neighbours' vectors for the replicas only.
    """
    if policy not in POLICIES:
        raise ValueError(policy)
    if assignment is not None:
        homes = assignment.where("is_home").select("vec_id", "n_homes")
        all_rows = graphs.join(homes, "vec_id")
        single = all_rows.where("n_homes = 1").select("vec_id", "nbrs", F.lit(1).alias("n_homes"))
        shared = all_rows.where("n_homes > 1")
    else:
        single, shared = None, graphs
    lists = shared.groupBy("vec_id").agg(F.flatten(F.collect_list("nbrs")).alias("e"), F.count("*").cast("int").alias("n_homes"))
    distinct = F.array_sort(F.array_distinct(F.transform("e", lambda e: F.struct(e["d"].alias("d"), e["id"].alias("id")))))
    merged = lists.select("vec_id", _plain(distinct).alias("nbrs"), "n_homes")
    if policy == "nearest":
        merged = merged.withColumn("nbrs", F.slice("nbrs", 1, degree))
    elif policy == "hashed":
        keyed = F.array_sort(F.transform("nbrs", lambda e: F.struct(F.xxhash64("vec_id", e["id"]).alias("h"), e["id"].alias("id"), e["d"].alias("d"))))
        merged = merged.withColumn("nbrs", _plain(_nearest(_plain(F.slice(keyed, 1, degree)), degree)))
    elif policy == "reprune":
        merged = _repruned(merged, vectors, degree, alpha, col)
    return merged if single is None else single.unionByName(merged)


def _repruned(merged: DataFrame, vectors: DataFrame, degree: int, alpha: float, col: str) -> DataFrame:
    import numpy as np
    import pyarrow as pa

    from shardgraph.operators.arrays import lists, matrix
    from shardgraph.operators.builders.robust import prune

    edges = merged.select("vec_id", "n_homes", F.explode("nbrs").alias("e")).select("vec_id", "n_homes", "e.id", "e.d")
    full = edges.join(vectors.select(F.col("vec_id").alias("id"), F.col(col).alias("x")), "id").join(vectors.select("vec_id", F.col(col).alias("own")), "vec_id")

    def one(t: pa.Table) -> pa.Table:
        ids, d = t.column("id").to_numpy(), t.column("d").to_numpy()
        x = np.r_[matrix(t.column("own"))[:1], matrix(t.column("x"))]
        kept = prune(np.array([0]), np.arange(1, len(x))[None, :], x, degree, alpha, np.r_[np.int64(-1), ids])[0]
        kept = kept[kept >= 0] - 1
        nbrs = lists(pa.StructArray.from_arrays([pa.array(ids[kept]), pa.array(d[kept])], names=["id", "d"]), np.array([len(kept)]))
        return pa.table({"vec_id": t.column("vec_id").slice(0, 1), "nbrs": nbrs, "n_homes": t.column("n_homes").slice(0, 1)})

    return full.groupBy("vec_id").applyInArrow(one, "vec_id bigint, nbrs array<struct<id:bigint,d:double>>, n_homes int")


def write_nodes(graph: DataFrame, vectors: DataFrame, path: str, files: int, col: str = "q") -> None:
    """Node records (vector and edges) in id ranges, sorted inside, so reads by id prune row groups."""
    nodes = graph.join(vectors.select("vec_id", F.col(col).alias("embedding")), "vec_id")
    nodes.repartitionByRange(files, "vec_id").sortWithinPartitions("vec_id").write.mode("overwrite").parquet(path)


def order_violations(graphs: DataFrame, position: str = "pos") -> DataFrame:
    """Rows (shard_id, violations): records of a shard's stream that come after one with a larger id.

    A merge that reads the streams side by side would pair the wrong records there; grouping by id
    does not, and this check makes a bad stream visible.
    """
    before = F.lag("vec_id").over(Window.partitionBy("shard_id").orderBy(position))
    return graphs.withColumn("bad", (before > F.col("vec_id")).cast("int")).groupBy("shard_id").agg(F.coalesce(F.sum("bad"), F.lit(0)).cast("bigint").alias("violations"))
