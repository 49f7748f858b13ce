"""Streams over events of any span and order of files."""

from datetime import datetime, timedelta

from edgegraph import streaming
from edgegraph.plans import Scratch

START = datetime(2024, 1, 1)
SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string"


def events():
    days = range(0, 300, 50)  # a click and a purchase half an hour later, every 50 days
    return [(2 * d + i, START + timedelta(days=d, minutes=30 * i), 1, t) for d in days for i, t in enumerate(("click", "purchase"))]


def test_dedupe_over_a_long_table_is_distinct(spark, tmp_path):
    spark.createDataFrame(events(), SCHEMA).write.parquet(f"{tmp_path}/events.parquet")
    got = streaming.op_stream_dedupe(spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == [(1, "click"), (1, "purchase")]


def test_join_keeps_pairs_of_files_out_of_order(spark, tmp_path, monkeypatch):
    spark.createDataFrame(events(), SCHEMA).write.parquet(f"{tmp_path}/events.parquet")

    def backwards(spark, d, files=4, late=None):
        scratch = Scratch(spark, "stream")
        for row in reversed(events()):
            frame = spark.createDataFrame([row], SCHEMA.replace("_ntz", ""))
            frame.coalesce(1).write.mode("append").parquet(f"{scratch.path}/in")
        return spark.readStream.schema(frame.schema).option("maxFilesPerTrigger", 3).parquet(f"{scratch.path}/in"), scratch

    monkeypatch.setattr(streaming, "_source", backwards)
    got = streaming.op_stream_join(spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == [(2 * d, 2 * d + 1) for d in range(0, 300, 50)]


def test_levels_fill_from_the_smallest():
    assert streaming.fill_level([5, 1, 3], 4) == [0, 3, 1] and streaming.fill_level([0, 0], 3) == [2, 1]
    assert streaming.fill_level([9, 1], 0) == [0, 0] and streaming.fill_level([4, 4, 4], 1) == [1, 0, 0]


def test_arriving_edges_go_to_a_home_or_the_smallest_part(spark):
    edges = lambda rows: spark.createDataFrame(rows, "src long, dst long")
    placed = spark.createDataFrame([(1, 2, 0)] + [(100 + i, 200 + i, 1) for i in range(50)], "src long, dst long, part int")
    got = {(r.src, r.dst): r.part for r in streaming.assign_arriving(edges([(2, 3), (100, 900), (1, 2)] + [(1000 + i, 2000 + i) for i in range(60)]), placed, 3).collect()}
    assert got[2, 3] == 0 and got[100, 900] == 1 and (1, 2) not in got
    fresh = [p for (a, _), p in got.items() if a >= 1000]
    assert 1 not in fresh and abs(fresh.count(0) - fresh.count(2)) < 20


def test_labels_merge_batch_by_batch(spark, tmp_path):
    links = [[(1, 2), (3, 4), (8, 9)], [(2, 3), (9, 7)], [(5, 6), (6, 1)], [(7, 7)]]
    parents = None
    for i, batch in enumerate(links):
        streaming.merge_arriving(spark.createDataFrame(batch, "a long, b long"), parents).write.mode("append").parquet(f"{tmp_path}/p")
        parents = spark.read.schema("label long, parent long").parquet(f"{tmp_path}/p")
    got = streaming.current_labels(spark.createDataFrame([(v,) for v in range(1, 11)], "vid long"), parents)
    assert {r.vid: r.comp for r in got.collect()} == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 6: 1, 7: 7, 8: 7, 9: 7, 10: 10}
