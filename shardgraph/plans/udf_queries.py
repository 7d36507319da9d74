"""Queries of the user-defined functions, with SQL twins."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from shardgraph.functions import vectors as v
from shardgraph.functions.udf import ExpandNeighbors, Preference, centroid, register, vec_dist, vec_dist_arrow
from shardgraph.plans.methods import BASE, EPS, NEED, G, _graphs, labelled
from shardgraph.registry import CORE
from shardgraph.sources import tables

DIST_SQL = f"{BASE} select vec_id, shard_id, d2 from p where r <= 2"


def _pairs(spark, sf_dir):
    vecs, c = labelled(spark, sf_dir)
    cents = spark.createDataFrame([(i, [int(x) for x in row]) for i, row in enumerate(c)], "shard_id int, c array<int>")
    return vecs.crossJoin(F.broadcast(cents))


def _top2(rows):
    from pyspark.sql import Window

    return rows.withColumn("r", F.row_number().over(Window.partitionBy("vec_id").orderBy("d2", "shard_id"))).where("r <= 2").drop("r")


@CORE.query("udf_vec_dist", DIST_SQL)
def q_udf_vec_dist(spark, sf_dir):
    return _top2(_pairs(spark, sf_dir).select("vec_id", "shard_id", vec_dist("q", "c").alias("d2")))


@CORE.query("udf_vec_dist_arrow", DIST_SQL)
def q_udf_vec_dist_arrow(spark, sf_dir):
    return _top2(_pairs(spark, sf_dir).select("vec_id", "shard_id", vec_dist_arrow("q", "c").alias("d2")))


@CORE.query("udf_is_needed", f"{BASE}, h as (select vec_id, d2 as hd from p where r = 1) select p.vec_id, p.shard_id from p join h using (vec_id) where r > 1 and p.d2 * {EPS.denominator**2} < hd * {EPS.numerator**2}")
def q_udf_is_needed(spark, sf_dir):
    register(spark)
    d = _pairs(spark, sf_dir).select("vec_id", "shard_id", v.l2sq(F.col("q"), F.col("c")).alias("d2"))
    from pyspark.sql import Window

    w = Window.partitionBy("vec_id").orderBy("d2", "shard_id")
    ranked = d.withColumn("hd", F.first("d2").over(w)).withColumn("r", F.row_number().over(w))
    return ranked.where("r > 1").where(F.expr(f"is_needed(hd, d2, {EPS.numerator}, {EPS.denominator})")).select("vec_id", "shard_id")


@CORE.query("udaf_centroid", f"{BASE} select label, pos - 1 as pos, x::bigint as x from m")
def q_udaf_centroid(spark, sf_dir):
    g = tables.e64q(spark, sf_dir).groupBy("label").agg(centroid("q").alias("c"))
    return g.select("label", F.posexplode("c").alias("pos", "x"))


@CORE.query("udtf_preference", f"{BASE} select vec_id, shard_id, d2, r::int as rank from p where r <= 3")
def q_udtf_preference(spark, sf_dir):
    vecs, c = labelled(spark, sf_dir)
    spark.udtf.register("preference", Preference)
    cents = spark.createDataFrame([([[int(x) for x in row] for row in c],)], "cs array<array<int>>")
    vecs.crossJoin(F.broadcast(cents)).createOrReplaceTempView("_pref_in")
    return spark.sql("select vec_id, p.shard_id, p.d2, p.rank from _pref_in, lateral preference(q, cs) p where p.rank <= 3")


@CORE.query("udtf_expand_neighbors", f"{BASE}, {NEED}, {G} select vec_id, nbr, d2 from g")
def q_udtf_expand(spark, sf_dir):
    """Edges of all shard graphs, one row each."""
    spark.udtf.register("expand_neighbors", ExpandNeighbors)
    _graphs(spark, sf_dir)[2].createOrReplaceTempView("_edges_in")
    return spark.sql("select e.vec_id, e.nbr, e.d2 from _edges_in, lateral expand_neighbors(_edges_in.vec_id, nbrs) e")


def _shard_kernel(t: pa.Table) -> pa.Table:
    n = pa.array([t.num_rows], pa.int64())
    return pa.table({"shard_id": t.column("shard_id").slice(0, 1), "n": n, "first_id": pa.array([min(t.column("vec_id").to_pylist())], pa.int64())})


@CORE.query("grouped_kernel", f"{BASE} select shard_id, count(*)::bigint as n, min(vec_id) as first_id from p where r = 1 group by shard_id")
def q_grouped_kernel(spark, sf_dir):
    from shardgraph.plans.methods import open_partition

    homes = open_partition(spark, sf_dir, max_homes=1).select("shard_id", "vec_id")
    return homes.groupBy("shard_id").applyInArrow(_shard_kernel, "shard_id int, n bigint, first_id bigint")


def iter_squares(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Norms of vectors batch by batch, the smallest ``mapInArrow`` kernel."""
    for b in batches:
        x = np.asarray(b.column("q").flatten().to_numpy(zero_copy_only=False), np.int64).reshape(b.num_rows, -1)
        yield pa.RecordBatch.from_pydict({"vec_id": b.column("vec_id"), "n2": pa.array((x * x).sum(axis=1))})


@CORE.query("map_kernel", "with v as (select vec_id, list_transform(embedding, lambda x: cast(floor(x::double * 1000 + 0.5) as bigint)) as q from embeddings) select vec_id, list_sum(list_transform(q, lambda x: x * x))::bigint as n2 from v")
def q_map_kernel(spark, sf_dir):
    return tables.e64q(spark, sf_dir).select("vec_id", "q").mapInArrow(iter_squares, "vec_id bigint, n2 bigint")
