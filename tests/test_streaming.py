"""Streams: windows that close, batches that run again, late data."""

from pyspark.sql import functions as F

from cityweave.context import context
from cityweave.streaming import feeds


def test_closed_windows_come_out_once(spark, city, tmp_path):
    """In append mode a window comes when the watermark has passed it; the open ones at the end stay in."""
    feed = feeds.changes(spark, city.sf_dir)
    feeds.run(feeds.tumbling(feed), f"{tmp_path}", feeds._append(f"{tmp_path}"))
    got = spark.read.parquet(f"{tmp_path}/data")
    batch = city.city.table("events").groupBy(F.window(F.col("ts").cast("timestamp"), "1 hour")).count()
    assert got.groupBy("window", "change").count().where("count > 1").count() == 0
    assert 0 < got.agg(F.sum("n")).first()[0] <= batch.agg(F.sum("count")).first()[0]


def test_incremental_graph_equals_a_rebuild(spark, city, tmp_path):
    """Subjects replaced, deleted and brought back over batches, one of them run again and one out of order."""
    labels = city.city.crowd.select("area_id", F.lit("cw:label").alias("p"), F.col("label").alias("o")).where("o is not null")
    write = feeds.incremental_graph(f"{tmp_path}", lambda keys: labels.join(keys, "area_id", "left_semi"))
    kind = F.create_map(*[F.lit(x) for pair in feeds.CHANGES.items() for x in pair])
    rows = city.city.table("events").select(F.col("event_id").cast("long").alias("event_id"), F.col("user_id").cast("long").alias("area_id"), "event_type", kind[F.col("event_type")].alias("change"))
    parts = [rows.where("event_id < 300"), rows.where("event_id >= 600"), rows.where("event_id between 300 and 599"), rows.where("event_id < 50")]
    state = lambda: {(r.s, r.p, r.o) for r in feeds.graph_state(spark, f"{tmp_path}").collect()}
    for number, part in enumerate(parts):
        write(part, number)
        once = state()
        write(part, number)
        assert state() == once
    last = rows.groupBy("area_id").agg(F.max_by("event_type", "event_id").alias("o")).collect()
    named = {r.area_id: r.o for r in labels.collect()}
    live = {r.area_id: r.o for r in last if r.o != "error"}
    assert 0 < len(live) < len(last)
    want = {(f"cw:crowd/way/{k}", "cw:lastChange", o) for k, o in live.items()} | {(f"cw:crowd/way/{k}", "cw:label", named[k]) for k in live if k in named}
    assert state() == want
    versions = {}
    for folder in tmp_path.glob("state/version=*/bucket=*"):
        versions.setdefault(folder.name, []).append(folder.parent.name)
    assert max(map(len, versions.values())) <= 2


def test_silent_footprints_are_forgotten(spark, city, tmp_path):
    """With a short time to live few states are left; what came out for the others stays."""
    kept = {}
    for ttl in (1, 24 * 365):
        sink = f"{tmp_path}/{ttl}"
        q = feeds.run(feeds.latest_state(feeds.changes(spark, city.sf_dir), ttl), sink, feeds._append(sink), "update")
        got = spark.read.parquet(f"{sink}/data").groupBy("area_id").agg(F.max("event_id").alias("e"))
        want = city.city.table("events").groupBy("user_id").agg(F.max("event_id").alias("e"))
        assert {tuple(r) for r in got.collect()} == {tuple(r) for r in want.collect()}
        kept[ttl] = [op["numRowsTotal"] for p in q.recentProgress for op in p["stateOperators"]][-1]
    assert kept[1] < kept[24 * 365]


def test_context_is_shared(spark, city):
    assert context(spark, city.sf_dir) is city
