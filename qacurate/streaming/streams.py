"""Incremental forms of the methods, on file streams.

Event times of the given tables carry no zone; they are cast to session-zone timestamps before a
watermark is set. Every query has a checkpoint of its own.
"""

from __future__ import annotations

import json

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from qacurate.functions.text import shingles
from qacurate.operators import minhash as M
from qacurate.operators.decontam import decontaminate
from qacurate.staging import Staged, fresh_path, released_shuffles, remove

WATERMARK = "10 minutes"


def file_stream(spark: SparkSession, path: str, schema: StructType, files: int = 1, time: str | None = None) -> DataFrame:
    """A stream over Parquet files, ``files`` per batch; the schema is given, never guessed."""
    out = spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(path)
    return out if time is None else out.withColumn(time, F.col(time).cast("timestamp"))


def split_files(df: DataFrame, path: str, order: str, parts: int = 4) -> None:
    """Writes a table as files in ascending order of a column, so that a stream meets them as they came."""
    low, high = df.agg(F.min(order), F.max(order)).first()
    number = lambda c: F.unix_micros(c.cast("timestamp")) if "timestamp" in dict(df.dtypes)[order] else c.cast("long")
    a, b = df.select(number(F.lit(low)), number(F.lit(high))).first() if low is not None else (0, 1)
    cell = F.least(F.floor((number(F.col(order)) - a) * parts / max(b - a, 1)), F.lit(parts - 1))
    for k in range(parts):
        df.where(cell == k).coalesce(1).write.mode("append").parquet(path)


def drain(out: DataFrame, mode: str, name: str) -> tuple[DataFrame, list[dict]]:
    """Runs a stream to its end into a table in the shared folder; returns it and the progress of each batch."""
    spark = out.sparkSession
    path = fresh_path(spark, name)
    if mode == "append":
        q = out.writeStream.format("parquet").option("path", path).option("checkpointLocation", fresh_path(spark, f"{name}-state")).outputMode(mode).trigger(availableNow=True).start()
    else:
        def keep(batch: DataFrame, _: int) -> None:
            batch.write.mode("overwrite").parquet(path)

        q = out.writeStream.foreachBatch(keep).option("checkpointLocation", fresh_path(spark, f"{name}-state")).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(out.schema).parquet(path), [json.loads(p.json) for p in q.recentProgress]


def run_once(out: DataFrame, mode: str, name: str) -> DataFrame:
    return drain(out, mode, name)[0]


def counters(progress: list[dict]) -> dict[str, int]:
    """Rows read and rows that came too late for the state, over all batches, and what ``observe`` counted by name."""
    seen = {"rows_read": sum(p["numInputRows"] for p in progress), "rows_late": sum(o["numRowsDroppedByWatermark"] for p in progress for o in p["stateOperators"])}
    for p in progress:
        for stage, values in (p.get("observedMetrics") or {}).items():
            for name, n in values.items():
                seen[f"{stage}.{name}"] = seen.get(f"{stage}.{name}", 0) + (n or 0)
    return seen


def counted(df: DataFrame, stage: str) -> DataFrame:
    """The same rows, counted as they pass: ``counters`` has the sum as ``<stage>.n``."""
    return df.observe(stage, F.count(F.lit(1)).alias("n"))


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    g = events.groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return g.select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    g = events.groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n"))
    return g.select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "1 day") -> DataFrame:
    g = events.groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n"))
    return g.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n")


def dedup_within(events: DataFrame, keys: list[str], horizon: str = "2 hours") -> DataFrame:
    """The first event of each key within the horizon; state is dropped behind the watermark."""
    return events.withWatermark("ts", horizon).dropDuplicatesWithinWatermark(keys)


def join_streams(left: DataFrame, right: DataFrame, within: str = "1 hour") -> DataFrame:
    """(user_id, t1, t2): right events of a user within an interval after left ones; both sides forget by watermark."""
    x = left.select(F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", WATERMARK)
    y = right.select(F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", WATERMARK)
    return x.join(y, F.expr(f"u1 = u2 and t2 >= t1 and t2 <= t1 + interval {within}")).select(F.col("u1").alias("user_id"), "t1", "t2")


class IncrementalScores:
    """(qid, n, total): a question's scores, emitted once ``full`` have come, or by what has come when ``wait`` is over.

    Scores are (qid, score, ts). The wait is in event time, from a question's last score on. A finished question
    is remembered until then, so that further scores of it count for nothing, and is forgotten afterwards:
    state does not outlive the wait. Rows behind the watermark, that of the batches before, are left out. The
    state is a table that each batch joins and writes anew, keyed by batch, so a repeated batch overwrites its own.
    """

    def __init__(self, spark: SparkSession, full: int = 16, wait: str = "1 day") -> None:
        self.spark, self.full = spark, full
        self.span, self.delay = (int(pd.Timedelta(x).total_seconds() * 1_000_000) for x in (wait, WATERMARK))
        self.state, self.seen, self.out = (fresh_path(spark, x) for x in ("score-state", "score-seen", "score-out"))
        self.batches = 0

    def _mark(self, batch_id: int) -> int | None:
        """The watermark of the batches before, in microseconds."""
        if batch_id == 0:
            return None
        top = self.spark.read.schema("u long, batch int").parquet(self.seen).where(F.col("batch") < batch_id).agg(F.max("u")).first()[0]
        return None if top is None else top - self.delay

    def _held(self, batch_id: int, like: DataFrame) -> DataFrame:
        schema = f"qid {like.schema['qid'].dataType.simpleString()}, n long, total long, last long"
        return self.spark.createDataFrame([], schema) if batch_id == 0 else self.spark.read.schema(schema).parquet(f"{self.state}/batch={batch_id - 1}")

    def add(self, batch: DataFrame, batch_id: int) -> None:
        mark = self._mark(batch_id)
        rows = batch.select("qid", "score", F.unix_micros("ts").alias("u"))
        held = self._held(batch_id, batch)
        timely = rows if mark is None else rows.where(F.col("u") > mark)
        placed = timely.withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy("u")))
        before = held.select("qid", F.col("n").alias("_n"), F.col("total").alias("_total"), F.col("last").alias("_last"))
        room = F.col("r") <= self.full - F.coalesce("_n", F.lit(0))
        came = placed.join(before.select("qid", "_n"), "qid", "left").groupBy("qid").agg(F.count_if(room).alias("more"), F.sum(F.when(room, F.col("score")).otherwise(0)).alias("plus"), F.max("u").alias("u"))
        zero = F.lit(0).cast("long")
        both = before.join(came, "qid", "full").select(
            "qid", F.coalesce("_n", zero).alias("was"), (F.coalesce("_n", zero) + F.coalesce("more", zero)).alias("n"), (F.coalesce("_total", zero) + F.coalesce("plus", zero)).cast("long").alias("total"), F.greatest("_last", "u").alias("last"), F.col("u").isNull().alias("quiet")
        )
        over = F.lit(False) if mark is None else F.col("quiet") & (F.col("last") + self.span < mark)
        table = Staged(both.withColumn("over", over), "score-batch")
        done = (~F.col("over") & (F.col("was") < F.col("n")) & (F.col("n") == self.full)) | (F.col("over") & (F.col("n") < self.full))
        table.df.where(done).select("qid", "n", "total").write.mode("overwrite").parquet(f"{self.out}/batch={batch_id}")
        table.df.where(~F.col("over")).select("qid", "n", "total", "last").write.mode("overwrite").parquet(f"{self.state}/batch={batch_id}")
        rows.agg(F.max("u").alias("u")).write.mode("overwrite").parquet(f"{self.seen}/batch={batch_id}")
        table.drop()
        if batch_id > 1:
            remove(self.spark, f"{self.state}/batch={batch_id - 2}")
        self.batches = batch_id + 1

    def run(self, stream: DataFrame) -> DataFrame:
        q = stream.writeStream.foreachBatch(self.add).option("checkpointLocation", fresh_path(self.spark, "score-checkpoint")).trigger(availableNow=True).start()
        q.awaitTermination()
        schema = f"qid {stream.schema['qid'].dataType.simpleString()}, n long, total long"
        if not self.batches:
            return self.spark.createDataFrame([], schema)
        self.add(self.spark.createDataFrame([], stream.schema), self.batches)  # what the last batch's watermark ends
        return self.spark.read.schema(schema).parquet(self.out).select("qid", "n", "total")


class IncrementalDedup:
    """MinHash deduplication by batches: a row goes if one that came before it is similar.

    Within a batch the smaller id comes first. A smaller id that comes late therefore goes when a larger one
    was there before: what has been decided stays. The index holds bands and sets of all rows and is
    keyed by batch, so a repeated batch overwrites what it wrote before. A batch reads the stored bands once,
    keeps those it shares, and takes only the sets of rows that they name. Pairs are ruled out by sizes and
    sketches before both sets of one meet; what a batch has staged goes with it.
    """

    def __init__(self, spark: SparkSession, threshold: float = 0.6) -> None:
        self.spark, self.threshold = spark, threshold
        self.bands, self.sets, self.out = (fresh_path(spark, x) for x in ("index-bands", "index-sets", "index-out"))

    def _past(self, path: str, like: DataFrame, batch_id: int) -> DataFrame:
        """What earlier batches wrote; an empty table before the first."""
        if batch_id == 0:
            return like.limit(0)
        return self.spark.read.option("basePath", path).schema(like.withColumn("batch", F.lit(0)).schema).parquet(path).where(F.col("batch") < batch_id).drop("batch")

    def add(self, batch: DataFrame, batch_id: int) -> None:
        """batch: (id, text)"""
        coded = batch.select("id", shingles("text").alias("set")).withColumn("hset", M.hash_set())
        signed_table = Staged(M.minhash(coded, drop=True), "batch-sets")
        signed = signed_table.df
        bands_table = Staged(M.lsh_bands(signed), "batch-bands")
        bands, sets = bands_table.df, signed.select("id", "hset")
        before = self._past(self.bands, bands, batch_id)
        met = Staged(before.join(bands.select("band", "key").distinct(), ["band", "key"], "left_semi"), "bands-met")
        known = Staged(self._past(self.sets, sets, batch_id).join(met.df.select("id").distinct(), "id", "left_semi").unionByName(sets), "sets-met")
        rows = met.df.withColumn("old", F.lit(True)).unionByName(bands.withColumn("old", F.lit(False)))
        fits = M.sketched_pairs(rows, known.df, self.threshold)
        # The row of this batch goes, of two such rows the larger id.
        mine = signed.select(F.col("id").alias("b"), F.lit(True).alias("new"))
        named = fits.join(mine, "b", "left").select(F.when(F.col("new"), F.col("a")).otherwise(F.col("b")).alias("a"), F.when(F.col("new"), F.col("b")).otherwise(F.col("a")).alias("b"))
        pairs = Staged(named, "batch-pairs")
        gone = Staged(M.verify(pairs.df, known.df, self.threshold).groupBy(F.col("b").alias("id")).agg(F.min("a").alias("by")), "batch-gone")
        with released_shuffles(self.spark):
            signed.select("id").join(gone.df, "id", "left").select("id", F.coalesce("by", "id").alias("keep_id")).write.mode("overwrite").parquet(f"{self.out}/batch={batch_id}")
            bands.write.mode("overwrite").parquet(f"{self.bands}/batch={batch_id}")
            sets.write.mode("overwrite").parquet(f"{self.sets}/batch={batch_id}")
        for table in (signed_table, bands_table, met, known, pairs, gone):
            table.drop()

    def run(self, stream: DataFrame) -> DataFrame:
        q = stream.writeStream.foreachBatch(self.add).option("checkpointLocation", fresh_path(self.spark, "index-state")).trigger(availableNow=True).start()
        q.awaitTermination()
        return self.spark.read.parquet(self.out).select("id", "keep_id")


def incremental_decontaminate(stream: DataFrame, items: DataFrame) -> DataFrame:
    """Evidence of leaks of a stream of window questions (doc_id, id, words) against fixed items."""
    spark = stream.sparkSession
    path = fresh_path(spark, "leaks")

    def step(batch: DataFrame, batch_id: int) -> None:
        decontaminate(batch, items).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    q = stream.writeStream.foreachBatch(step).option("checkpointLocation", fresh_path(spark, "leaks-state")).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(path).select("doc_id", "item_id", "rank")
