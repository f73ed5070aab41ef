"""The estimators on Structured Streaming.

``window_sampled``    two chained stateful aggregates per window: values, then heads
``window_registers``  m registers per window, a state bounded whatever the stream
``window_probe``      a bounded heap of u occurrences per window, custom state
``running``           one versioned state table, merged by micro-batch and keyed by
                      batch id, so that a replayed batch changes nothing
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark import StorageLevel
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..functions.hashing import hash60, threshold
from ..operators.counters import HyperLogLog
from ..plans import duck
from ..sources.streams import element_stream, table

EVENT_SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def source(spark: SparkSession, path: str, files_per_batch: int = 1) -> DataFrame:
    """The events as a file stream with the schema given; event time as an instant,
    which watermarks need."""
    return spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_batch).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def _stream_of(events: DataFrame, element: str = "user_id", rate: float = 1.0, seed: int = 42) -> DataFrame:
    """``(ts, element, occ)``, sampled by the occurrence's hash before any state is kept."""
    out = element_stream(events, [F.col(element)], [F.col("event_id")], {"ts": F.col("ts")})
    return out if rate == 1 else out.where(hash60(F.col("occ"), "s", seed) < threshold(rate))


def _window(length: str, slide: str | None):
    return F.window("ts", length, slide) if slide else F.window("ts", length)


def window_sampled(events: DataFrame, length: str = "7 days", delay: str = "1 hour", slide: str | None = None, element: str = "user_id", rate: float = 1.0) -> DataFrame:
    """Heads of the coverage estimator per closed window, tumbling or, with ``slide``, sliding."""
    x = _stream_of(events, element, rate).withWatermark("ts", delay)
    values = x.groupBy(_window(length, slide).alias("w"), "element").agg(F.count(F.lit(1)).alias("f"))
    return values.groupBy(F.window(F.window_time("w"), length) if slide is None else F.col("w")).agg(
        F.sum("f").alias("l"), F.count(F.lit(1)).alias("ns"), F.count_if(F.col("f") == 1).alias("e1"), F.count_if(F.col("f") == 2).alias("e2")).select(
        F.col("window.start").alias("start") if slide is None else F.col("w.start").alias("start"), "l", "ns", "e1", "e2")


def window_registers(events: DataFrame, m: int = 200, length: str = "7 days", delay: str = "1 hour", element: str = "user_id", rate: float = 1.0) -> DataFrame:
    """Register sums per closed window; ``HyperLogLog.formula`` turns them into a count."""
    hll = HyperLogLog(m)
    b, r = hll.registers(F.col("element"))
    x = _stream_of(events, element, rate).withWatermark("ts", delay)
    regs = x.groupBy(_window(length, None).alias("w"), b.alias("bucket")).agg(F.max(r).alias("rank"), F.count(F.lit(1)).alias("l"))
    sums = regs.groupBy(F.window(F.window_time("w"), length)).agg(F.count("rank").alias("used"), F.sum(F.pow(F.lit(2.0), -F.col("rank"))).alias("z"), F.sum("l").alias("l"))
    return sums.select(F.col("window.start").alias("start"), "l", hll.formula(F.col("used"), F.col("z")).alias("ns_hat"))


def session_sampled(events: DataFrame, gap: str = "6 hours", delay: str = "1 hour", key: str = "user_id", element: str = "event_type", rate: float = 1.0) -> DataFrame:
    """Heads of the coverage estimator of the elements in each key's sessions.  A session has
    few kinds of elements at a time, and its state holds their counts as one map per key:
    occurrences are gathered by the session window, and counted when it closes."""
    x = element_stream(events, [F.col(element)], [F.col("event_id")], {"ts": F.col("ts"), "key": F.col(key)})
    x = (x if rate == 1 else x.where(hash60(F.col("occ"), "s", 42) < threshold(rate))).withWatermark("ts", delay)
    s = x.groupBy(F.session_window("ts", gap).alias("s"), "key").agg(F.array_sort(F.collect_list("element")).alias("x"))
    f = F.transform(F.array_distinct("x"), lambda v: F.size(F.filter("x", lambda w: w == v)))
    once, twice = F.size(F.filter(f, lambda k: k == 1)).cast("long"), F.size(F.filter(f, lambda k: k == 2)).cast("long")
    return s.select(F.col("s.start").alias("start"), "key", F.size("x").cast("long").alias("l"), F.size(F.array_distinct("x")).cast("long").alias("ns"), once.alias("e1"), twice.alias("e2"))


def probe_processor(u: int) -> type[StatefulProcessor]:
    class Probe(StatefulProcessor):
        """Keeps the u lowest (value hash, occurrence hash) pairs of one salt of a window;
        emits them when the watermark passes its end."""

        def init(self, handle: StatefulProcessorHandle) -> None:
            self.handle = handle
            self.low = handle.getValueState("low", "pairs array<struct<v:long,o:long>>, l long, until long")

        def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
            pairs, seen, until = ([], 0, 0)
            if self.low.exists():
                old = self.low.get()
                pairs, seen, until = [(p[0], p[1]) for p in old[0]], old[1], old[2]
            for batch in rows:
                pairs += list(zip(batch["v"].tolist(), batch["o"].tolist()))
                pairs = sorted(pairs)[:u]
                seen += len(batch)
                end = int(batch["until"].max())
                if end != until:
                    self.handle.registerTimer(end)
                    until = end
            self.low.update(([(int(a), int(b)) for a, b in pairs], int(seen), int(until)))
            yield pd.DataFrame()

        def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:
            if not self.low.exists():
                yield pd.DataFrame()
                return
            pairs, seen, _ = self.low.get()
            self.low.clear()
            # the salt's rows are told once, on its first pair
            yield pd.DataFrame({"start": [key[0]] * len(pairs), "l": [seen] + [0] * (len(pairs) - 1), "v": [p[0] for p in pairs], "o": [p[1] for p in pairs]})

        def close(self) -> None:
            pass

    return Probe


def window_probe(events: DataFrame, u: int = 100, length: str = "7 days", delay: str = "1 hour", element: str = "user_id", seed: int = 42, salts: int = 16) -> DataFrame:
    """The lowest u pairs of every salt of each closed window: a window's rows are dealt to
    ``salts`` tasks by occurrence, each with a state of u pairs.  ``probe_heads`` merges them."""
    x = _stream_of(events, element).withWatermark("ts", delay)
    x = x.select(F.window("ts", length).alias("w"), hash60(F.col("element"), "v", seed).alias("v"), hash60(F.col("occ"), "u", seed).alias("o"), "ts")
    x = x.select(F.col("w.start").cast("string").alias("start"), F.pmod("o", F.lit(salts)).alias("salt"), (F.unix_millis("w.end")).alias("until"), "v", "o", "ts")
    return x.groupBy("start", "salt").transformWithStateInPandas(
        statefulProcessor=probe_processor(u)(), outputStructType="start string, l long, v long, o long", outputMode="append", timeMode="EventTime")


def probe_heads(parts: DataFrame, u: int) -> DataFrame:
    """``(start, l, u, u1, u2)`` of each window from the pairs of its salts: at most salts x u rows a window."""
    length = parts.groupBy("start").agg(F.sum("l").alias("l"))
    low = parts.withColumn("k", F.row_number().over(W.partitionBy("start").orderBy("v", "o"))).where(F.col("k") <= u)
    per = low.groupBy("start", "v").agg(F.count(F.lit(1)).alias("f"))
    heads = per.groupBy("start").agg(F.sum("f").alias("u"), F.count_if(F.col("f") == 1).alias("u1"), F.count_if(F.col("f") == 2).alias("u2"))
    return length.join(heads, "start")


class Running:
    """The unwindowed estimate: registers, reservoir and length in a versioned folder."""

    def __init__(self, path: str, m: int = 200, u: int = 500, seed: int = 42):
        self.path, self.m, self.u, self.seed = path, m, u, seed
        self.hll = HyperLogLog(m, seed)

    def _versions(self, spark: SparkSession) -> list[int]:
        """Finished versions: a small table beside the states, to which one row is added
        after a state is whole."""
        try:
            done = spark.read.schema("version long").parquet(f"{self.path}/versions")
        except AnalysisException as error:
            if error.getCondition() != "PATH_NOT_FOUND":
                raise
            return []
        return sorted({r["version"] for r in done.collect()})

    def state(self, spark: SparkSession, before: int | None = None) -> DataFrame | None:
        done = [v for v in self._versions(spark) if before is None or v < before]
        return spark.read.parquet(f"{self.path}/v{done[-1]}") if done else None

    def fold(self, sample: DataFrame, batch_id: int) -> None:
        """Merges one batch; writing version ``batch_id`` again replaces it by the same."""
        spark = sample.sparkSession
        b, r = self.hll.registers(F.col("element"))
        # the batch is read and hashed once; four numbers a row are kept for its three uses
        rows = sample.select(b.cast("long").alias("b"), r.cast("long").alias("r"), hash60(F.col("element"), "v", self.seed).alias("v"), hash60(F.col("occ"), "u", self.seed).alias("o")).persist(StorageLevel.MEMORY_AND_DISK)
        none, zero = F.lit(None).cast("long"), F.lit(0).cast("long")
        regs = rows.groupBy(F.col("b").alias("k")).agg(F.max("r").alias("v"), F.count(F.lit(1)).alias("n"))
        pairs = rows.orderBy("v", "o").limit(self.u).select(F.lit("pair").alias("kind"), zero.alias("k"), "v", "o")
        length = regs.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("v")).select(F.lit("length").alias("kind"), zero.alias("k"), "v", none.alias("o"))
        new = regs.select(F.lit("register").alias("kind"), "k", "v", none.alias("o")).unionByName(pairs).unionByName(length)
        old = self.state(spark, batch_id)
        rows = new if old is None else new.unionByName(old.select("kind", "k", "v", "o"))
        merged = rows.where("kind = 'register'").groupBy("kind", "k").agg(F.max("v").alias("v")).withColumn("o", F.lit(None).cast("long"))
        merged = merged.unionByName(rows.where("kind = 'pair'").orderBy("v", "o").limit(self.u))
        merged = merged.unionByName(rows.where("kind = 'length'").groupBy("kind", "k").agg(F.sum("v").alias("v")).withColumn("o", F.lit(None).cast("long")))
        # at most m + u + 1 rows
        merged.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/v{batch_id}")
        rows.unpersist()
        spark.createDataFrame([(batch_id,)], "version long").coalesce(1).write.mode("append").parquet(f"{self.path}/versions")

    def estimate(self, spark: SparkSession) -> DataFrame:
        s = self.state(spark)
        regs = s.where("kind = 'register'").agg(F.count(F.lit(1)).alias("used"), F.sum(F.pow(F.lit(2.0), -F.col("v"))).alias("z"))
        per = s.where("kind = 'pair'").groupBy("v").agg(F.count(F.lit(1)).alias("f"))
        heads = per.agg(F.sum("f").alias("u"), F.count_if(F.col("f") == 1).alias("u1"))
        length = s.where("kind = 'length'").select(F.col("v").alias("l"))
        out = length.crossJoin(regs).crossJoin(heads).withColumn("ns_hat", self.hll.formula(F.col("used"), F.col("z")))
        return out.select("l", "u", "u1", "ns_hat", F.try_divide("ns_hat", 1 - F.col("u1") / F.col("u")).alias("n_hat"))

    def start(self, events: DataFrame, checkpoint: str, rate: float = 1.0, element: str = "user_id"):
        sample = _stream_of(events, element, rate).drop("ts")
        return sample.writeStream.foreachBatch(lambda df, i: self.fold(df, i)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def scratch(spark: SparkSession) -> str:
    """A new folder that all executors see: under the session's checkpoint folder where it
    has one; a cluster without it is refused, as a machine's own folder loses data there."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not base:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file:///tmp/checkpoints"
    return f"{base.rstrip('/')}/live-{uuid.uuid4().hex}"


#: Custom state needs the store with column families; a query keeps the one it was started with.
STORE, ROCKS = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def finish(df: DataFrame, mode: str = "append", custom_state: bool = False) -> DataFrame:
    """Runs a stream over what is there and returns its output as a table."""
    spark = df.sparkSession
    at, before = scratch(spark), spark.conf.get(STORE)
    if custom_state:
        spark.conf.set(STORE, ROCKS)
    try:
        q = df.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/log").outputMode(mode).trigger(availableNow=True).start()
    finally:
        spark.conf.set(STORE, before)
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{at}/out")


def late_rows(query) -> int:
    """Rows that came behind the watermark, over all batches that are still reported."""
    return sum(int(s["numRowsDroppedByWatermark"]) for p in query.recentProgress for s in p["stateOperators"])


WEEK = "time_bucket(INTERVAL 7 DAY, ts, TIMESTAMP '1970-01-01')"


def closing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stream of the events and, in a later batch, one row far behind them in time, which
    closes all their windows.  The first batch takes all files of the events."""
    at = scratch(spark)
    events = table(spark, sf_dir, "events")
    events.write.parquet(f"{at}/a")
    files = len(spark.read.parquet(f"{at}/a").inputFiles())
    end = events.limit(1).select(F.lit(-1).cast("long").alias("event_id"), F.expr("cast('2030-01-01' as timestamp_ntz)").alias("ts"), F.lit(-1).cast("long").alias("user_id"), F.lit("end").alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
    end.coalesce(1).write.parquet(f"{at}/b")
    return source(spark, f"{at}/*", max(files, 1))


def _closed(df: DataFrame) -> DataFrame:
    return df.where(F.year("start") < 2030).withColumn("start", F.date_format("start", "yyyy-MM-dd HH:mm:ss"))


def add_queries(query, sql) -> None:
    week = {"start": f"strftime({WEEK}, '%Y-%m-%d %H:%M:%S')"}
    by_week = duck.stream("user", week)

    @query("t_window_sampled", duck.heads(by_week, ["start"]))
    def _(spark, d):
        return _closed(finish(window_sampled(closing(spark, d))))

    @query("w11_stream", duck.heads(duck.sample(by_week, 0.5), ["start"]))
    def _(spark, d):
        """A stream of which half is processed: sampled before any state is kept."""
        return _closed(finish(window_sampled(closing(spark, d), rate=0.5)))

    @query("t_window_registers", sql(f"SELECT * FROM (SELECT start, count(*) AS l FROM ({by_week}) GROUP BY ALL) JOIN ({duck.hll(by_week, 200, ['start'])}) USING (start)", "ns_hat"))
    def _(spark, d):
        return _closed(finish(window_registers(closing(spark, d))))

    @query("t_window_probe", sql(f"SELECT start, l, u, u1, u2 FROM ({duck.probe(by_week, 500, 'value_hash', ['start'])}) JOIN (SELECT start, count(*) AS l FROM ({by_week}) GROUP BY ALL) USING (start)", "", "l u u1 u2"))
    def _(spark, d):
        out = probe_heads(finish(window_probe(closing(spark, d), 500), custom_state=True), 500)
        return _closed(out.withColumn("start", F.to_timestamp("start")))

    sliding = f"SELECT strftime(date_trunc('day', ts) - to_days(CAST(k AS INT)), '%Y-%m-%d %H:%M:%S') AS start, element, occ FROM ({duck.stream('user', {'ts': 'ts'})}), range(7) q(k)"

    @query("t_sliding", duck.heads(sliding, ["start"]))
    def _(spark, d):
        return _closed(finish(window_sampled(closing(spark, d), "7 days", "1 hour", "1 day")))

    marked = "SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY key ORDER BY ts, occ) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM ({})"
    numbered = "SELECT *, sum(fresh) OVER (PARTITION BY key ORDER BY ts, occ) AS run FROM ({})".format(marked.format(duck.stream("event_type", {"ts": "ts", "key": "user_id"})))
    sessions = f"SELECT strftime(min(ts) OVER (PARTITION BY key, run), '%Y-%m-%d %H:%M:%S') AS start, key, element, occ FROM ({numbered})"

    @query("t_session", f"SELECT *, CASE WHEN e1 < l THEN round(ns / (1 - e1 / l), 6) END AS n_hat FROM ({duck.heads(sessions, ['start', 'key'])})")
    def _(spark, d):
        """The coverage estimate of event types in each user's sessions."""
        out = _closed(finish(session_sampled(closing(spark, d))))
        return out.withColumn("n_hat", F.try_divide(F.col("ns").cast("double"), 1 - F.col("e1") / F.col("l")))

    digits = "SELECT CAST(user_id % 100 AS VARCHAR) AS element, CAST(event_id AS VARCHAR) AS occ FROM events WHERE user_id IS NOT NULL"

    @query("t_rate_source", duck.heads(digits))
    def _(spark, d):
        """The events in ten batches, at the rate of a file each, into the ``memory`` sink: heads of a hundred classes of users."""
        at, name = scratch(spark), f"heads_{uuid.uuid4().hex}"
        table(spark, d, "events").repartition(10, "event_id").write.parquet(f"{at}/in")
        x = source(spark, f"{at}/in").where("user_id IS NOT NULL")
        values = x.select((F.col("user_id") % 100).alias("element")).groupBy("element").agg(F.count(F.lit(1)).alias("f"))
        q = values.writeStream.format("memory").queryName(name).outputMode("complete").option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.table(name).agg(F.coalesce(F.sum("f"), F.lit(0)).alias("l"), F.count(F.lit(1)).alias("ns"), F.count_if(F.col("f") == 1).alias("e1"), F.count_if(F.col("f") == 2).alias("e2"))

    @query("t_running", sql(f"SELECT l, u, u1, ns_hat, ns_hat / (1 - u1 / u) AS n_hat FROM (SELECT count(*) AS l FROM ({duck.stream('user')})), ({duck.hll(duck.stream('user'), 200)}), ({duck.probe(duck.stream('user'), 500, 'value_hash')})", "ns_hat n_hat", "l u u1"))
    def _(spark, d):
        at = scratch(spark)
        parts = table(spark, d, "events").repartition(3, "event_id")
        parts.write.parquet(f"{at}/in")
        r = Running(f"{at}/state")
        r.start(source(spark, f"{at}/in"), f"{at}/log").awaitTermination()
        return r.estimate(spark)
