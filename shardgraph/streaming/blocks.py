"""Vectors as a stream: a micro-batch is a block of the partitioner, or new vectors to route."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from shardgraph.operators.centroids import preferences
from shardgraph.operators.partition import PartitionConfig, ShardPlan, assign_homes, assign_replicas
from shardgraph.operators.state import LOG_SCHEMA, ClusterState, radius_boost
from shardgraph.workspace import Workspace


class BlockAssigner:
    """``foreachBatch`` handler: homes, state, quotas and replicas of one block, replay-safe.

    Output and state log are written under the batch id. A batch that is delivered again finds its
    log, takes the state before it from the previous batch's log, and overwrites its own rows.
    """

    def __init__(self, out: str, centroids: np.ndarray, plan: ShardPlan, cfg: PartitionConfig, total: int, start: ClusterState):
        self.out, self.centroids, self.plan, self.cfg, self.total, self.start = out, centroids, plan, cfg, total, start

    def state_before(self, spark, batch_id: int) -> tuple[ClusterState, int]:
        s = ClusterState(self.start.capacity.copy(), self.start.sample_share.copy(), self.start.radius2.copy(), self.start.sample_weight)
        seen = 0
        if batch_id > 0:
            for r in spark.read.schema(LOG_SCHEMA).parquet(f"{self.out}/log/batch={batch_id - 1}").collect():
                s.n_orig[r.shard_id], s.n_repl[r.shard_id], s.replica_share[r.shard_id] = r.n_orig, r.n_repl, r.replica_share
                s.radius2[r.shard_id] = np.nan if r.radius is None else r.radius**2
            seen = int(s.n_orig.sum())
        return s, seen

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        ws = Workspace(spark, "block")
        state, seen = self.state_before(spark, batch_id)
        prefs = ws.write(preferences(batch, self.centroids), "prefs")
        homes, counts, far = assign_homes(prefs, state.room, ws, "h")
        homes = ws.write(homes, "homes")
        state.update(counts, far)
        seen += int(counts.sum())
        state.refresh_quota(max(0, self.total - seen), self.cfg.quota, self.cfg.lo, self.cfg.hi, self.cfg.margin, self.cfg.fixed_share)
        boost = radius_boost(min(batch_id + 1, self.cfg.blocks), self.cfg.blocks, self.cfg.boost, self.cfg.b0, self.cfg.p)
        more = assign_replicas(homes, state, self.cfg, boost, ws, "r")
        rows = homes.select("vec_id", "shard_id", F.lit(True).alias("is_home"), "dist").unionByName(more.select("vec_id", "shard_id", F.lit(False).alias("is_home"), "dist"))
        rows.write.mode("overwrite").parquet(f"{self.out}/assignment/batch={batch_id}")
        spark.createDataFrame(state.rows(batch_id, boost), LOG_SCHEMA).coalesce(1).write.mode("overwrite").parquet(f"{self.out}/log/batch={batch_id}")


def partition_stream(stream: DataFrame, assigner: BlockAssigner, checkpoint: str):
    q = stream.writeStream.foreachBatch(assigner).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def route_inserts(stream: DataFrame, centroids: np.ndarray, out: str, checkpoint: str, col: str = "q"):
    """New vectors go to the pending rows of their nearest shard under frozen centroids; no state."""
    near = preferences(stream, centroids, 1, col=col).select("vec_id", F.get("prefs", F.lit(0)).alias("p")).select("vec_id", "p.shard_id", F.col("p.dist").alias("dist"))
    q = near.writeStream.format("parquet").option("path", out).option("checkpointLocation", checkpoint).partitionBy("shard_id").trigger(availableNow=True).start()
    q.awaitTermination()
    return q
