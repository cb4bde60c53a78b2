"""Streams: parties that arrive one after the other, records that arrive by block, and event-time windows."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from blindmatch.operators import clustering, kernels
from blindmatch.plans.lineage import shared_path


def run_to_table(stream: DataFrame, mode: str = "append", keep: list[str] | None = None) -> DataFrame:
    """Run a stream over all that is available and return what it wrote. Append mode writes files; complete mode keeps the last batch;
    update mode keeps each batch, of which the last row of every key (``keep``) counts."""
    spark = stream.sparkSession
    path, check = shared_path(spark, "stream"), shared_path(spark, "stream-check")
    writer = stream.writeStream.option("checkpointLocation", check).trigger(availableNow=True)
    if mode == "append":
        q = writer.outputMode("append").format("parquet").option("path", path).start()
    elif mode == "update":
        q = writer.outputMode("update").foreachBatch(lambda df, i: df.withColumn("_batch", F.lit(i)).write.mode("overwrite").parquet(f"{path}/batch-{i}")).start()
    else:
        q = writer.outputMode(mode).foreachBatch(lambda df, i: df.write.mode("overwrite").parquet(path)).start()
    q.awaitTermination()
    if mode == "update":
        rest = [c for c in stream.columns if c not in keep]
        rows = spark.read.parquet(f"{path}/batch-*")
        return rows.groupBy(*keep).agg(*(F.max_by(c, "_batch").alias(c) for c in rest)).select(*stream.columns)
    return spark.read.schema(stream.schema).parquet(path)


def file_stream(spark: SparkSession, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def cluster_arriving_parties(spark: SparkSession, path: str, schema, s_t: float = 0.8) -> DataFrame:
    """Each micro-batch is one party: its records extend the stored clusters. A batch writes its own version of the clusters, named by
    its id, so a repeated batch gives the same table."""
    root, check = shared_path(spark, "arrivals"), shared_path(spark, "arrivals-check")
    state: dict[str, DataFrame] = {}

    def one(batch: DataFrame, i: int) -> None:
        rows = batch.select("block", "party", "rec_id", "words")
        party = rows.select("party").first()
        if party is None:
            return
        held = rows.unionByName(state["records"]) if state else rows
        if not state:
            found = clustering.cluster_early(rows, s_t, ord=[party[0]], mode="block")
        else:
            found = clustering.extend(state["clusters"], held, party[0], s_t)
        found.write.mode("overwrite").parquet(f"{root}/clusters-{i}")
        held.write.mode("overwrite").parquet(f"{root}/records-{i}")
        state["clusters"], state["records"] = (batch.sparkSession.read.parquet(f"{root}/{x}-{i}") for x in ("clusters", "records"))

    q = file_stream(spark, path, schema).writeStream.option("checkpointLocation", check).trigger(availableNow=True).foreachBatch(one).start()
    q.awaitTermination()
    return state["clusters"]


class BlockClusters(StatefulProcessor):
    """Keeps a block's records and their clusters; each batch's records are mapped party by party, best first for the batch.

    A cluster that already holds a record of a party is no candidate for another of it. The result depends on the batches,
    as it depends on the order of parties in a batch run.
    """

    def __init__(self, s_t: float = 0.8):
        self.s_t = s_t

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.members = handle.getMapState("members", "rec_id long", "party int, cluster_id long, words array<long>")

    def handleInputRows(self, key, rows, timer_values):
        new = pd.concat(list(rows)).sort_values(["party", "rec_id"])
        new = new[[not self.members.containsKey((int(r),)) for r in new.rec_id]]
        out = []
        for party, batch in new.groupby("party", sort=True):
            known = [(k[0], *v) for k, v in self.members.iterator()]
            taken = {c for _, p, c, _ in known if p == party}
            known = sorted((c, r, w) for r, _, c, w in known if c not in taken)
            words = np.array(batch.words.tolist(), np.int64).view(np.uint64)
            label = {int(r): int(r) for r in batch.rec_id}
            if known:
                have = np.array([k[2] for k in known], np.int64).view(np.uint64)
                ids = np.array([k[0] for k in known])
                starts = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
                score = kernels.cluster_scores(kernels.dice_matrix(words, have), starts, "average")
                r, c = np.nonzero(score >= self.s_t)
                for e in kernels.best_mapping(c, r, score[r, c]):
                    label[int(batch.rec_id.iloc[r[e]])] = int(ids[starts][c[e]])
            for rec, w in zip(batch.rec_id, batch.words):
                self.members.updateValue((int(rec),), (int(party), label[int(rec)], [int(x) for x in w]))
                out.append((key[0], int(party), int(rec), label[int(rec)]))
        yield pd.DataFrame(out, columns=["block", "party", "rec_id", "cluster_id"])

    def close(self) -> None:
        pass


def cluster_arriving_records(stream: DataFrame, s_t: float = 0.8) -> DataFrame:
    """A stream of masked records (block, party, rec_id, words) to block, party, rec_id, cluster_id."""
    spark = stream.sparkSession
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    return stream.groupBy("block").transformWithStateInPandas(BlockClusters(s_t), "block string, party int, rec_id long, cluster_id long", "Append", "None")


def tumbling(stream: DataFrame, size: str, late: str) -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", size), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.col("window.start").alias("from_ts"), "event_type", "n")


def sliding(stream: DataFrame, size: str, step: str, late: str) -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy(F.window("ts", size, step)).agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.col("window.start").alias("from_ts"), "n")


def sessions(stream: DataFrame, gap: str, late: str) -> DataFrame:
    w = stream.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))
    return w.select("user_id", F.col("session_window.start").alias("from_ts"), "n")
