"""Streaming forms: claims and sessions as stateful operators, dashboards over beats, a synthetic fleet as a source."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from ..functions.storage import scratch
from ..operators.index import DONE, FREE, HELD

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
REPLY = "tag string, sid long, item_id long, op string"


def use_rocksdb(spark: SparkSession) -> None:
    """State in RocksDB, which stateful processors need; a setting of the session that may change at run time."""
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


class ClaimMachine(StatefulProcessor):
    """One tag's atomic cell: the state partition that owns a tag is its only writer.

    Rows of a batch are taken in order of (sent, kind, seq, sid); kinds are SUBMIT, RELEASE, CONTACT and UPLOAD.
    """

    ORDER = {"RELEASE": 0, "UPLOAD": 1, "SUBMIT": 2, "CONTACT": 3}

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.cell = handle.getValueState("cell", StructType([StructField("state", IntegerType()), StructField("holder", LongType()), StructField("epoch", IntegerType())]))

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        pdf = pd.concat(list(rows))
        pdf = pdf.assign(o=pdf["kind"].map(self.ORDER)).sort_values(["sent", "o", "seq", "sid"])
        state, holder, epoch = self.cell.get() if self.cell.exists() else (FREE, None, 0)
        out = []
        for kind, sid, item, e in zip(pdf["kind"], pdf["sid"], pdf["item_id"], pdf["epoch"]):
            sid = int(sid)
            if kind in ("SUBMIT", "CONTACT"):
                if state == FREE:
                    state, holder = HELD, sid
                    out.append((sid, item, "RUN"))
                elif kind == "SUBMIT":
                    out.append((sid, item, "RUN" if state == HELD and holder == sid else "PARK"))
            elif kind == "RELEASE" and state == HELD and holder == sid:
                state, holder, epoch = FREE, None, epoch + 1
            elif kind == "UPLOAD":
                ok = state == HELD and holder == sid and int(e) == epoch
                state = DONE if ok else state
                out.append((sid, item, "OK" if ok else "REJECT"))
        self.cell.update((state, holder, epoch))
        if out:
            yield pd.DataFrame({"tag": [key[0]] * len(out), "sid": [o[0] for o in out], "item_id": [int(o[1]) for o in out], "op": [o[2] for o in out]})

    def close(self) -> None:
        pass


def claim_stream(events: DataFrame) -> DataFrame:
    """Replies to a stream of (tag, kind, sid, item_id, sent, seq, epoch)."""
    return events.groupBy("tag").transformWithStateInPandas(ClaimMachine(), REPLY, "append", "none")


def request_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1000) -> DataFrame:
    """The documents of all clients as a stream of submissions, one per client and content within a batch."""
    schema = spark.read.parquet(f"{sf_dir}/documents.parquet").schema
    docs = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("recursiveFileLookup", "true").parquet(f"{sf_dir}/documents.parquet*")
    sid = F.substring("source", 4, 20).cast("long")
    return docs.where("text IS NOT NULL").select(F.sha2("text", 256).alias("tag"), F.lit("SUBMIT").alias("kind"), sid.alias("sid"), F.col("doc_id").alias("item_id"), F.pmod(sid * 7919 + 17, F.lit(20000)).alias("sent"), F.col("doc_id").alias("seq"), F.lit(0).alias("epoch"))


class SessionMachine(StatefulProcessor):
    """One client's session: an event-time timer at its last beat plus the timeout; when it fires the client is lost."""

    def __init__(self, timeout_ms: int):
        self.timeout = timeout_ms

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.handle = handle
        self.last = handle.getValueState("last", StructType([StructField("ms", LongType())]))

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:
        newest = max(int(pdf["ms"].max()) for pdf in rows)
        before = self.last.get()[0] if self.last.exists() else None
        if before is None or newest > before:
            if before is not None:
                self.handle.deleteTimer(before + self.timeout)
            self.last.update((newest,))
            self.handle.registerTimer(newest + self.timeout)
        return iter(())

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
        last = self.last.get()[0]
        self.last.clear()
        yield pd.DataFrame({"sid": [int(key[0])], "last_ms": [last], "lost_ms": [last + self.timeout]})

    def close(self) -> None:
        pass


def loss_stream(beats: DataFrame, timeout_ms: int, delay: str = "0 seconds") -> DataFrame:
    """(sid, last_ms, lost_ms) from a stream of (sid, ts): silences found as the watermark passes them."""
    timed = beats.withWatermark("ts", delay).select("sid", "ts", F.unix_millis("ts").alias("ms"))
    return timed.groupBy("sid").transformWithStateInPandas(SessionMachine(timeout_ms), "sid long, last_ms long, lost_ms long", "append", "eventtime")


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Beats (sid, ts, beat_id) as a stream of the events table's files."""
    raw = spark.readStream.schema(EVENTS).parquet(f"{sf_dir}/events.parquet*")
    return raw.select(F.col("user_id").alias("sid"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("beat_id"))


def session_windows(beats: DataFrame, timeout: str, delay: str | None = None) -> DataFrame:
    """(sid, start, last_beat, n) by session windows whose gap is the timeout; batch or stream."""
    timed = beats.withWatermark("ts", delay) if delay else beats
    return timed.groupBy("sid", F.session_window("ts", timeout)).agg(F.max("ts").alias("last_beat"), F.count(F.lit(1)).alias("n")).select("sid", F.col("session_window.start").alias("start"), "last_beat", "n")


def beats_per_window(beats: DataFrame, length: str, slide: str | None = None) -> DataFrame:
    """(start, n): beats per tumbling or sliding window."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return beats.groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "n")


def once_per_request(requests: DataFrame, delay: str) -> DataFrame:
    """A stream of requests (sid, tag, ts) without retries that arrive within the delay."""
    return requests.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["sid", "tag"])


def late_rows(batch: DataFrame, seen_until) -> DataFrame:
    """Rows of a micro-batch older than what is closed already: counted aside, never applied."""
    return batch.where(F.col("ts") < seen_until)


def run_to_table(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Runs a stream over all that is there, in as many batches as its source makes, and returns the rows it wrote."""
    spark = stream.sparkSession
    out, checkpoint = scratch(spark, "stream-out"), scratch(spark, "stream-checkpoint")
    schema = stream.schema

    def save(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number}")  # a batch that is run again replaces itself

    query = stream.writeStream.outputMode(mode).foreachBatch(save).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    if query.exception():
        raise query.exception()
    return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(out)


class FleetSource(DataSource):
    """Data source ``fleet``: the plan of a synthetic fleet, or its beats as a stream.

    Options: clients, seed, delay_ms (latest arrival), fail_percent, joiners, beat_ms.
    """

    @classmethod
    def name(cls) -> str:
        return "fleet"

    def schema(self) -> str:
        return "sid long, online_ms long, fail_ms long, joins boolean"

    def reader(self, schema) -> DataSourceReader:
        return _FleetReader(self.options)

    def simpleStreamReader(self, schema) -> SimpleDataSourceStreamReader:
        return _FleetStream(self.options)


def _plan(options, sid: int) -> tuple:
    import hashlib

    number = lambda what: int.from_bytes(hashlib.sha256(f"{options.get('seed', 17)}:{what}:{sid}".encode()).digest()[:6], "big")
    n, delay = int(options.get("clients", 10)), int(options.get("delay_ms", 20000))
    online = number("online") % max(delay, 1)
    fails = number("fail") % 100 < int(options.get("fail_percent", 0))
    return sid, online, online + number("when") % max(delay, 1) if fails else None, sid >= n


def fleet_of(ids: DataFrame, **options) -> DataFrame:
    """(sid, online_ms, fail_ms, joins): the plan that the data source ``fleet`` gives by the same options, for the given ids (sid)."""

    def plan(batches):
        for b in batches:
            rows = [_plan(options, sid) for sid in b.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(list(zip(*rows)) or [()] * 4, (pa.int64(), pa.int64(), pa.int64(), pa.bool_()))], ["sid", "online_ms", "fail_ms", "joins"])

    return ids.select(F.col("sid").cast("long").alias("sid")).where("sid IS NOT NULL").mapInArrow(plan, "sid long, online_ms long, fail_ms long, joins boolean")


class _FleetReader(DataSourceReader):
    def __init__(self, options):
        self.options = options

    def partitions(self):
        n = int(self.options.get("clients", 10)) + int(self.options.get("joiners", 0))
        return [InputPartition((i, min(i + 1000, n))) for i in range(0, n, 1000)] or [InputPartition((0, 0))]

    def read(self, partition):
        for sid in range(*partition.value):
            yield _plan(self.options, sid)


class _FleetStream(SimpleDataSourceStreamReader):
    """Clients in order of their numbers, a few with every batch."""

    def __init__(self, options):
        self.options = options

    def initialOffset(self):
        return {"sid": 0}

    def read(self, start):
        n = int(self.options.get("clients", 10)) + int(self.options.get("joiners", 0))
        end = min(n, start["sid"] + int(self.options.get("per_batch", 5)))
        return iter([_plan(self.options, s) for s in range(start["sid"], end)]), {"sid": end}

    def readBetweenOffsets(self, start, end):
        return iter([_plan(self.options, s) for s in range(start["sid"], end["sid"])])

    def commit(self, end):
        pass
