"""Change feeds over the events table, as Structured Streaming, with batch forms to hold them against.

An event is a change of the footprint that its user_id names: signup is an
insert, view, click and purchase are updates, error is a delete. Event times
come without a zone and are taken as UTC.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce
from typing import TYPE_CHECKING

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

if TYPE_CHECKING:
    from cityweave.context import Context

EVENT = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
WATERMARK = "1 hour"
CHANGES = {"signup": "insert", "view": "update", "click": "update", "purchase": "update", "error": "delete"}


def _file_schema(spark: SparkSession, src_dir: str, pattern: str):
    return spark.read.option("pathGlobFilter", pattern).parquet(src_dir).schema


def changes(spark: SparkSession, src_dir: str, pattern: str = "events.parquet*", per_trigger: int = 1, schema=None, end_dir: str | None = None) -> DataFrame:
    """The feed: change events with a watermark. `end_dir`: a folder for markers, whose times move the watermark on after the last event."""
    schema = schema or _file_schema(spark, src_dir, pattern)
    read = spark.readStream.schema(schema).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", per_trigger).option("recursiveFileLookup", True)
    kind = F.create_map(*[F.lit(x) for pair in CHANGES.items() for x in pair])
    e = read.parquet(src_dir)
    if end_dir:
        e = e.unionByName(spark.readStream.schema(schema).parquet(end_dir))
    return e.select(F.col("event_id").cast("long").alias("event_id"), F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").cast("long").alias("area_id"), "event_type", kind[F.col("event_type")].alias("change"), "value").withWatermark("ts", WATERMARK)


def run(df: DataFrame, sink_dir: str, write: Callable[[DataFrame, int], None], mode: str = "append", checkpoint: str | None = None) -> StreamingQuery:
    """Works through all that is there; each batch is handed to `write` with its number."""
    q = df.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", checkpoint or f"{sink_dir}/_checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    return q


def _append(sink_dir: str) -> Callable[[DataFrame, int], None]:
    """Each batch to a folder of its own: a batch that runs twice overwrites itself."""
    return lambda df, batch: df.write.mode("overwrite").parquet(f"{sink_dir}/data/batch={batch}")


def _sink(c: Context, name: str) -> str:
    return f"{c.scratch.base}/stream-{name}-{c.scratch.count}"


def _collected(c: Context, name: str, df: DataFrame, mode: str = "append") -> DataFrame:
    sink = _sink(c, name)
    c.scratch.count += 1
    run(df, sink, _append(sink), mode)
    return c.spark.read.schema(df.schema).parquet(f"{sink}/data").select(df.columns)


def _closed(c: Context, name: str, windows: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Windows in append mode, all of them: each is written once, when the watermark has passed it, and its state goes.

    When the feed has been worked through, a marker far behind the last event
    goes into the stream, which then goes on from its checkpoint and closes the
    windows still open. The marker's own window stays open.
    """
    sink = _sink(c, name)
    c.scratch.count += 1
    end = f"{sink}/end"
    place = c.spark._jvm.org.apache.hadoop.fs.Path(end)
    place.getFileSystem(c.spark._jsc.hadoopConfiguration()).mkdirs(place)
    events = c.city.table("events")
    df = windows(changes(c.spark, c.sf_dir, end_dir=end))
    run(df, sink, _append(sink))
    last = events.agg(F.max("ts").alias("ts")).where("ts is not null")
    other = [F.lit(None).cast(f.dataType).alias(f.name) for f in events.schema if f.name != "ts"]
    marker = last.select((F.col("ts") + F.expr("interval 30 days")).cast(events.schema["ts"].dataType).alias("ts"), *other).select(events.columns)
    marker.write.mode("append").parquet(end)
    run(df, sink, _append(sink))
    return c.spark.read.schema(df.schema).parquet(f"{sink}/data").select(df.columns)


def tumbling(feed: DataFrame, width: str = "1 hour") -> DataFrame:
    return feed.groupBy(F.window("ts", width), "change").agg(F.count("*").alias("n"))


def sliding(feed: DataFrame, width: str = "1 hour", step: str = "15 minutes") -> DataFrame:
    return feed.groupBy(F.window("ts", width, step), "change").agg(F.count("*").alias("n"))


def sessions(feed: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return feed.groupBy(F.session_window("ts", gap).alias("window"), "area_id").agg(F.count("*").alias("n"))


def _windowed(df: DataFrame, *names: str) -> DataFrame:
    text = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss.SSSSSS")
    return df.select(text("window.start").alias("start"), text("window.end").alias("end"), *names, "n")


def deduplicated(feed: DataFrame) -> DataFrame:
    """Redelivered events once; ids are remembered as long as the watermark lasts."""
    return feed.dropDuplicatesWithinWatermark(["event_id"])


def with_links(feed: DataFrame, links: DataFrame) -> DataFrame:
    """The surfaces that a changed footprint is linked to: stream against table."""
    return feed.join(links.select("area_id", "surface_id"), "area_id").select("event_id", "area_id", "surface_id")


def signup_to_purchase(feed: DataFrame, within: str = "1 hour") -> DataFrame:
    """Purchases within a time after a signup of the same footprint: stream against stream."""
    s = feed.where("event_type = 'signup'").select(F.col("area_id").alias("s_area"), F.col("ts").alias("s_ts"), F.col("event_id").alias("signup"))
    p = feed.where("event_type = 'purchase'").select("area_id", "ts", F.col("event_id").alias("purchase"))
    return p.join(s, F.expr(f"area_id = s_area and ts >= s_ts and ts <= s_ts + interval {within}")).select("purchase", "signup")


STATE = "area_id long, event_id long, event_type string"


def _latest(ttl_ms: int):
    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        """Keeps the event with the greatest id of a footprint; a state of one row, until the watermark has passed its time to live."""
        if state.hasTimedOut:
            state.remove()
            return
        best, seen = state.get if state.exists else (-1, ""), 0
        for frame in batches:
            top = frame.loc[frame["event_id"].idxmax()]
            seen = max(seen, int(frame["ts"].max().timestamp() * 1000))
            if top["event_id"] > best[0]:
                best = (int(top["event_id"]), str(top["event_type"]))
        state.update(best)
        state.setTimeoutTimestamp(max(seen, state.getCurrentWatermarkMs()) + ttl_ms)
        yield pd.DataFrame({"area_id": [key[0]], "event_id": [best[0]], "event_type": [best[1]]})

    return step


def latest_state(feed: DataFrame, ttl_hours: float = 24 * 7) -> DataFrame:
    """The last event of each footprint. One that is silent for ttl_hours of event time is forgotten; what was put out for it stays."""
    step = _latest(int(ttl_hours * 3_600_000))
    return feed.where("area_id is not null").groupBy("area_id").applyInPandasWithState(step, STATE, "event_id long, event_type string", "update", GroupStateTimeout.EventTimeTimeout)


#: What else is said of footprints: their keys (area_id) to (area_id, p, o).
Described = Callable[[DataFrame], DataFrame]


def incremental_graph(sink_dir: str, described: Described | None = None, buckets: int = 8) -> Callable[[DataFrame, int], None]:
    """Keeps the triples of each footprint up to date: its last change, and what `described` says of it.

    All triples of a changed footprint are replaced, those of a deleted one go;
    of several events the greatest id counts, also over batches, for which a
    deleted footprint keeps a row without predicate. Touched buckets are written
    anew. A bucket's version is the batch's number, so a batch that runs again
    writes the same folders; readers take each bucket's latest version. Of the
    versions before the batch one is kept for that, older ones are removed.
    """

    def write(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        event = F.max_by(F.struct("event_type", "change"), "event_id")
        last = batch.where("area_id is not null").groupBy("area_id").agg(event.alias("e"), F.max("event_id").alias("event_id"))
        last = last.select("area_id", F.concat(F.lit("cw:crowd/way/"), F.col("area_id").cast("string")).alias("s"), "e.event_type", "e.change", "event_id").withColumn("bucket", F.pmod(F.xxhash64("s"), F.lit(buckets)))
        before = graph_state(spark, sink_dir, number, deleted=True)
        columns = ["s", "p", "o", "event_id", "bucket"]
        kept = None
        if before is not None:
            touched = before.join(last.select("bucket").distinct(), "bucket", "left_semi")
            known = touched.groupBy("s").agg(F.max("event_id").alias("old"))
            last = last.join(known, "s", "left").where("old is null or event_id > old").drop("old")
            kept = touched.join(last.select("s"), "s", "left_anti").select(columns)
        live = last.where("change <> 'delete'")
        parts = [live.select("s", F.lit("cw:lastChange").alias("p"), F.col("event_type").alias("o"), "event_id", "bucket")]
        parts.append(last.where("change = 'delete'").select("s", F.lit(None).cast("string").alias("p"), F.lit(None).cast("string").alias("o"), "event_id", "bucket"))
        if described:
            parts.append(described(live.select("area_id")).join(live, "area_id").select(columns))
        rows = reduce(DataFrame.unionByName, parts + ([kept] if kept is not None else []))
        rows.withColumn("version", F.lit(number)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("version", "bucket").parquet(f"{sink_dir}/state")
        _drop_old_versions(spark, f"{sink_dir}/state", number)

    return write


def _drop_old_versions(spark: SparkSession, path: str, number: int) -> None:
    """Leaves of each bucket the version `number` and the last one before it."""
    jvm = spark._jvm
    fs = jvm.org.apache.hadoop.fs.Path(path).getFileSystem(spark._jsc.hadoopConfiguration())
    found: dict[str, list[tuple[int, object]]] = {}
    for status in fs.globStatus(jvm.org.apache.hadoop.fs.Path(f"{path}/version=*/bucket=*")) or []:
        place = status.getPath()
        found.setdefault(place.getName(), []).append((int(place.getParent().getName().removeprefix("version=")), place))
    for versions in found.values():
        below = max((v for v, _ in versions if v < number), default=-1)
        for v, place in versions:
            if v < below:
                fs.delete(place, True)


def graph_state(spark: SparkSession, sink_dir: str, below: int | None = None, deleted: bool = False) -> DataFrame | None:
    """Triples of the latest version of each bucket (before version `below`), with the rows of deleted subjects if asked for."""
    path = spark._jvm.org.apache.hadoop.fs.Path(f"{sink_dir}/state")
    if not path.getFileSystem(spark._jsc.hadoopConfiguration()).exists(path):
        return None
    rows = spark.read.schema("s string, p string, o string, event_id long, version int, bucket int").parquet(f"{sink_dir}/state")
    if below is not None:
        rows = rows.where(F.col("version") < below)
    newest = rows.groupBy("bucket").agg(F.max("version").alias("version"))
    rows = rows.join(newest, ["bucket", "version"]).select("s", "p", "o", "event_id", "bucket")
    return rows if deleted else rows.where("p is not null")


# Queries. Each runs the stream to its end and reads what it wrote.
def _feed(c: Context) -> DataFrame:
    return changes(c.spark, c.sf_dir)


#: Events of one stretch of time, and stretches at most: the query's progress keeps a hundred batches.
STRETCH_ROWS, STRETCHES = 1 << 20, 40


def _stretches(events: DataFrame) -> list[DataFrame]:
    """The events by stretches of time of about as many rows, earliest first; those without a time are in the first."""
    n = min(STRETCHES, max(1, -(-events.count() // STRETCH_ROWS)))
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    cuts = events.agg(F.percentile_approx(at, [k / n for k in range(1, n)]).alias("cuts")).first()[0] if n > 1 else []
    cuts = sorted(set(cuts or []))
    place = reduce(lambda x, y: x + y, [F.coalesce(at > cut, F.lit(False)).cast("int") for cut in cuts], F.lit(0))
    return [events.where(place == k) for k in range(len(cuts) + 1)]


def _late(c: Context) -> DataFrame:
    """Events that come after the watermark has passed them: dropped, and counted from the query's progress.

    A batch is judged by the watermark that the batch before began with, so one
    event on time comes between the table and the late ones. The table comes
    in stretches of time, each in a file of its own and in order, so that
    nothing of it is late itself, whatever its files are.
    """
    source = f"{_sink(c, 'late')}-in"
    events = c.city.table("events")
    late = events.where("event_id < 50").withColumn("event_id", -F.col("event_id") - 1)
    last = events.orderBy(F.desc("ts"), F.desc("event_id")).limit(1).withColumn("event_id", F.col("event_id") + (1 << 40))
    for k, part in enumerate([*_stretches(events), last, late]):
        # files are taken up in the order they were written in
        part.coalesce(1).write.mode("overwrite").parquet(f"{source}/{k}")
    sink = _sink(c, "late")
    c.scratch.count += 1
    q = run(deduplicated(changes(c.spark, source, "*.parquet", schema=events.schema)), sink, _append(sink))
    dropped = sum(int(op["numRowsDroppedByWatermark"]) for p in q.recentProgress for op in p["stateOperators"])
    return c.spark.createDataFrame([(dropped,)], "dropped long")


def _redelivered(c: Context) -> DataFrame:
    return _collected(c, "dedup", deduplicated(_feed(c).union(_feed(c)))).select("event_id", "area_id", "event_type")


def _states(c: Context) -> DataFrame:
    found = _collected(c, "latest", latest_state(_feed(c)), "update")
    return found.groupBy("area_id").agg(F.max("event_id").alias("event_id"), F.max_by("event_type", "event_id").alias("event_type"))


def _incremental(c: Context) -> DataFrame:
    sink = _sink(c, "graph")
    c.scratch.count += 1
    labels = c.city.crowd.select("area_id", F.lit("cw:label").alias("p"), F.col("label").alias("o")).where("o is not null")
    run(_feed(c), sink, incremental_graph(sink, lambda keys: labels.join(keys, "area_id", "left_semi")))
    return graph_state(c.spark, sink).select("s", "p", "o")


QUERIES: dict[str, Callable[[Context], DataFrame]] = {
    "st_tumbling": lambda c: _windowed(_closed(c, "tumbling", tumbling), "change"),
    "st_sliding": lambda c: _windowed(_closed(c, "sliding", sliding), "change"),
    "st_session": lambda c: _windowed(_closed(c, "session", sessions), "area_id"),
    "st_dedup": _redelivered,
    "st_static_join": lambda c: _collected(c, "static", with_links(_feed(c), c.links.edges)),
    "st_interval_join": lambda c: _collected(c, "interval", signup_to_purchase(_feed(c))),
    "st_latest_state": _states,
    "st_late_count": _late,
    "st_incremental_graph": _incremental,
}


def oracle() -> dict[str, str]:
    from cityweave import oracles

    kind = "case event_type " + " ".join(f"when '{k}' then '{v}'" for k, v in CHANGES.items()) + " end as change"
    window = lambda start, width: f"{start} as start, {start} + interval {width} as \"end\""
    zoned = lambda sql, names: f"select strftime(start, '%Y-%m-%d %H:%M:%S.%f') as start, strftime(\"end\", '%Y-%m-%d %H:%M:%S.%f') as \"end\", {names}, n from ({sql})"
    return {
        "st_tumbling": zoned(f"select {window('time_bucket(interval 1 hour, ts)', '1 hour')}, {kind}, count(*) as n from events group by 1, 2, 3", "change"),
        "st_sliding": zoned(f"select {window('time_bucket(interval 15 minutes, ts) - k * interval 15 minutes', '1 hour')}, {kind}, count(*) as n from events, range(4) r(k) group by 1, 2, 3", "change"),
        "st_session": zoned("""select min(ts) as start, max(ts) + interval 30 minutes as "end", area_id, count(*) as n from (
            select *, sum(fresh) over (partition by area_id order by ts rows unbounded preceding) as session from (
              select ts, user_id::bigint as area_id, case when lag(ts) over (partition by user_id order by ts) > ts - interval 30 minutes then 0 else 1 end as fresh from events)) group by area_id, session""", "area_id"),
        "st_dedup": "select distinct event_id::bigint as event_id, user_id::bigint as area_id, event_type from events",
        "st_static_join": oracles.q("select event_id::bigint as event_id, area_id, surface_id from events join edges on area_id = user_id"),
        "st_interval_join": "select p.event_id::bigint as purchase, s.event_id::bigint as signup from events p join events s on p.user_id = s.user_id and p.ts >= s.ts and p.ts <= s.ts + interval 1 hour where p.event_type = 'purchase' and s.event_type = 'signup'",
        "st_latest_state": "select user_id::bigint as area_id, max(event_id)::bigint as event_id, arg_max(event_type, event_id) as event_type from events group by 1",
        "st_late_count": "select count(*) as dropped from events where event_id < 50",
        "st_incremental_graph": oracles.q("""select s, p, o from (
            with live as (select user_id, arg_max(event_type, event_id) as o from events group by 1 having arg_max(event_type, event_id) <> 'error')
            select 'cw:crowd/way/' || user_id as s, 'cw:lastChange' as p, o from live
            union all select 'cw:crowd/way/' || user_id, 'cw:label', label from live join crowd on area_id = user_id where label is not null)"""),
    }
