"""Structured Streaming around releases: histograms, policy monitors and buckets that are emitted when they are full.

Sources are file streams; ``run_available`` drains what is there and stops, so a stream over a finished folder equals the
batch query. Nothing here is claimed by the method: searches are not incremental, so a drift leads to a new search.
"""

from __future__ import annotations

import collections
import heapq
import itertools
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from capbuckets.operators import policy, search

SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, files_per_batch: int = 1) -> DataFrame:
    """The events table as a stream; ``ts`` is a timestamp, as watermarks need."""
    raw = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files_per_batch).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def checkpoint_path(spark: SparkSession, name: str) -> str:
    """A new folder for a stream's state: below the shared checkpoint folder; one of our own only where none is named and all run in one process."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not root:
        if spark.sparkContext.master.partition("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        root = f"file://{tempfile.mkdtemp(prefix='capbuckets-stream-')}"
    return f"{root.rstrip('/')}/stream-{name}-{uuid.uuid4().hex}"


def run_available(df: DataFrame, mode: str = "append", name: str = "out") -> DataFrame:
    """Runs a stream over all that is available, into Parquet by batch; the last batch stands in ``complete`` mode."""
    spark = df.sparkSession
    path = checkpoint_path(spark, name)

    def keep(batch: DataFrame, epoch: int) -> None:
        out = f"{path}/data" if mode != "complete" else f"{path}/data/{epoch}"
        batch.write.mode("append" if mode != "complete" else "overwrite").parquet(out)
        if mode == "complete":
            latest[0] = out

    latest = [f"{path}/data"]
    run = df.writeStream.outputMode(mode).option("checkpointLocation", f"{path}/state").foreachBatch(keep).trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(df.schema).parquet(latest[0])


def stream_histogram(stream: DataFrame, width: float = 4.0, top: int = 49) -> DataFrame:
    """(v, cnt) of the sensitive bands, kept up as state."""
    v = F.least(F.lit(top), F.floor(F.col("value") / width)).cast("int")
    return stream.groupBy(v.alias("v")).agg(F.count(F.lit(1)).alias("cnt"))


def policy_monitor(hist: DataFrame, theta: int, on_change: Callable[[search.Layout, bool], None], m_max: int = 50):
    """Starts a monitor of a histogram stream: after each batch the policy is tested, and searched anew if the optimum may have moved."""
    last: list[tuple] = []

    def test(batch: DataFrame, epoch: int) -> None:
        batch.persist()
        caps = policy.linear_caps(batch, theta, 2, 100)
        feasible = policy.caps_feasible(caps).first().feasible
        layout = search.search_two_size(caps, m_max)
        state = (feasible, tuple(layout.classes))
        if state != (last[-1] if last else None):
            last.append(state)
            on_change(layout, feasible)
        batch.unpersist()

    return hist.writeStream.outputMode("complete").option("checkpointLocation", checkpoint_path(hist.sparkSession, "monitor")).foreachBatch(test).trigger(availableNow=True).start()


class BucketFiller(StatefulProcessor):
    """Holds rows of a group back until a bucket of ``size`` rows can be made in which no value exceeds ``quota`` copies.

    A bucket takes the earliest rows that its quotas allow. Rows wait in one queue a value, and a heap has the head of each, so
    a bucket costs its own rows however many wait; as a bucket follows from the rows up to its last one, it is made when that came.
    """

    def __init__(self, size: int, quota: int):
        self.size, self.quota = size, quota

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.waiting = handle.getListState("waiting", "event_id bigint, v int")
        self.made = handle.getValueState("made", "n bigint")

    def take(self, queues: dict, heads: list) -> list[tuple]:
        """(event_id, v) of the next bucket, out of the queues; nothing, and the queues as they were, if it cannot be filled yet."""
        taken, counts, full = [], {}, []
        while heads and len(taken) < self.size:
            _, v = heapq.heappop(heads)
            taken.append((v, queues[v].popleft()))
            counts[v] = counts.get(v, 0) + 1
            if queues[v] and counts[v] < self.quota:
                heapq.heappush(heads, (queues[v][0][0], v))
            elif queues[v]:
                full.append(v)
        done = len(taken) == self.size
        if not done:
            for v, row in reversed(taken):
                queues[v].appendleft(row)
            full = [v for v in queues if queues[v]]
        for v in full:
            heapq.heappush(heads, (queues[v][0][0], v))
        return [(i, v) for v, (_, i) in taken] if done else []

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        queues, heads, place = {}, [], itertools.count()
        n = int(self.made.get()[0]) if self.made.exists() else 0
        whole = lambda x: None if pd.isna(x) else int(x)
        kept = [(whole(i), whole(v)) for i, v in self.waiting.get()] if self.waiting.exists() else []
        for frame in itertools.chain([kept], rows):
            came = frame if frame is kept else zip(*[[whole(x) for x in frame[c].tolist()] for c in ("event_id", "v")], strict=True)
            for i, v in came:
                at, queue = next(place), queues.setdefault(v, collections.deque())
                if not queue:
                    heapq.heappush(heads, (at, v))
                queue.append((at, i))
            out = []
            while bucket := self.take(queues, heads):
                out += [(str(key[0]), n, i, v) for i, v in bucket]
                n += 1
            if out:
                part, bucket_of, ids, values = zip(*out, strict=True)
                yield pd.DataFrame({"part": part, "bucket": bucket_of, "event_id": pd.array(ids, "Int64"), "v": pd.array(values, "Int32")})
        left = [(i, v) for _, i, v in sorted(((at, i, v) for v, queue in queues.items() for at, i in queue), key=lambda r: r[0])]
        if left:
            self.waiting.put(left)
        else:  # a list that is kept must not be empty
            self.waiting.clear()
        self.made.update((n,))

    def close(self) -> None:
        pass


def bucket_fill(stream: DataFrame, size: int, quota: int, parts: int = 4) -> DataFrame:
    """(part, bucket, event_id, v): buckets in the order in which they fill; rows are spread over ``parts`` by their id."""
    keyed = stream.select(F.pmod(F.xxhash64("event_id"), F.lit(parts)).cast("string").alias("part"), "event_id", F.least(F.lit(49), F.floor(F.col("value") / 4.0)).cast("int").alias("v"))
    return keyed.groupBy("part").transformWithStateInPandas(statefulProcessor=BucketFiller(size, quota), outputStructType="part string, bucket bigint, event_id bigint, v int", outputMode="Append", timeMode="None")
