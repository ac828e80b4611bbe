"""Streams: rows beyond the watermark, and histograms kept up to date."""

import random
from datetime import datetime

from pyspark.sql import functions as F

from spanwalk.operators.edgemap import expand_counted, window_edges
from spanwalk.functions.predicates import Ordering
from spanwalk.plans.inspection import exchanges, plan_text
from spanwalk.sources.graphs import edges_frame
from spanwalk.streaming import contacts, histograms
from spanwalk.workloads.relational_queries import o_stream_dedup


def events(spark, rows, path):
    made = [(k, datetime(2024, 1, day, hour), 1, "click", 1.0, "{}") for k, (day, hour) in enumerate(rows)]
    spark.createDataFrame(made, contacts.EVENTS).coalesce(1).write.parquet(path)


def test_late_rows_count_nowhere(spark, tmp_path):
    """The fourth file holds a row of a day whose window is closed, and one of a day still open: lateness is told by the watermark that the batch before closed windows by."""
    for k, rows in enumerate(([(10, 1), (10, 2)], [(20, 1)], [(20, 2), (25, 0)], [(10, 3), (20, 3), (30, 0)])):
        events(spark, rows, str(tmp_path / str(k)))
    done = contacts.run_to_end(contacts.tumbling_counts(contacts.event_stream(spark, str(tmp_path / "*"))))
    got = {r.day: r.n for r in done.select(F.dayofmonth("w.start").alias("day"), "n").collect()}
    assert {k: got[k] for k in (10, 20, 25)} == {10: 2, 20: 3, 25: 1} and 30 not in got


def some(seed, m):
    r = random.Random(seed)
    return [(r.randrange(4) if r.random() < 0.6 else 0, r.randrange(5), s, s + r.choice([0, r.randint(0, 3000)])) for s in (r.choice([r.randint(-500, 9000), 7]) for _ in range(m))]


def wanted(rows, bins):
    """Cells by brute force."""
    out = {}
    for v in {e[0] for e in rows}:
        own = [(s, e - s) for x, _, s, e in rows if x == v]
        levels = []
        for axis in (0, 1):
            lo, hi = min(p[axis] for p in own), max(p[axis] for p in own)
            levels.append(next(k for k in range(64) if (hi >> k) - (lo >> k) < bins))
        for s, d in own:
            key = (v, *levels, s >> levels[0], d >> levels[1])
            out[key] = out.get(key, 0) + 1
    return out


def test_histograms_of_a_stream(spark, tmp_path):
    """Batches in any order, a retried batch and an empty one give the cells of all edges at once."""
    rows = sorted(some(1, 400), key=lambda e: -e[2])
    upkeep = histograms.HistogramUpkeep(spark, 10, root=str(tmp_path / "state"))
    parts = [rows[:50], rows[50:300], [], rows[300:]]
    for k, part in enumerate(parts):
        frame = edges_frame(spark, part) if part else edges_frame(spark, rows).limit(0)
        upkeep(frame, k)
        if k == 1:
            upkeep(frame, k)
    now = upkeep.current()
    assert {tuple(r[:5]): r.n for r in now.cells.select("v", "kx", "ky", "bx", "by", "n").collect()} == wanted(rows, 10)
    assert {r.v: r.m for r in now.ranges.collect()} == {v: sum(e[0] == v for e in rows) for v in {e[0] for e in rows}}
    assert not (tmp_path / "state" / "cells-0").exists() and (tmp_path / "state" / "cells-2").exists()
    busy = now.at_least(150)
    assert {r.v for r in busy.cells.collect()} == {0}
    asked = spark.createDataFrame([(0, -500, 20_000), (0, 20_000, 30_000), (0, 2000, 6000)], "v long, a long, b long")
    found = {(r.a, r.b): r.k_hat / r.m for r in busy.estimate(asked).collect()}
    own = [(s, e) for x, _, s, e in rows if x == 0]
    assert found[(-500, 20_000)] == 1 and found[(20_000, 30_000)] == 0
    assert abs(found[(2000, 6000)] - sum(s >= 2000 and e <= 6000 for s, e in own) / len(own)) < 0.15


def test_counters_and_plans(spark):
    edges = window_edges(edges_frame(spark, [(k % 9, k % 7, k, k + 3) for k in range(90)]))
    frontier = spark.createDataFrame([(0, 2, 40)], "source long, v long, label long")
    found, seen = expand_counted(frontier, edges, Ordering.STRICTLY_SUCCEEDS)
    rows = found.collect()
    assert seen.get == {"examined": 10, "admitted": len(rows)} and len(rows) == sum(k > 40 for k in range(2, 90, 9))
    moved = spark.range(10).groupBy((F.col("id") % 3).alias("g")).count()
    assert len(exchanges(moved)) == 1 and exchanges(moved)[0].startswith("hashpartitioning(") and exchanges(spark.range(3).toDF("x")) == []
    assert "HashAggregate" in plan_text(moved)


def contact_files(spark, folder):
    for k, rows in enumerate(([(10, 1), (10, 2)], [(11, 1)], [(10, 2), (12, 0)])):
        events(spark, rows, str(folder / str(k)))
    return contacts.event_stream(spark, str(folder / "*"))


def hours(df, t):
    return sorted((r.d, r.h) for r in df.select(F.dayofmonth(t).alias("d"), F.hour(t).alias("h")).collect())


def test_rows_of_a_stream_stay_off_the_driver(spark, tmp_path):
    """The sink's rows are read from files: the last batch's when complete, all batches' otherwise."""
    stream = contact_files(spark, tmp_path)
    sessions = contacts.run_to_end(contacts.session_counts(stream, late="10 days"), "complete")
    counts = contacts.run_to_end(stream.groupBy("user_id").agg(F.count("*").alias("n")), "update")
    for done in (sessions, counts):
        assert "Scan parquet" in plan_text(done)
    assert hours(sessions, "w.start") == [(10, 1), (10, 2), (11, 1), (12, 0)]
    assert sorted(r.n for r in sessions.collect()) == [1, 1, 1, 2] and sorted(r.n for r in counts.collect()) == [2, 3, 5]
    assert contacts.run_to_end(stream.where("false")).count() == 0


def test_kept_rows_stay_off_the_driver(spark, tmp_path):
    once = contacts.run_to_end(contacts.without_repeats(contact_files(spark, tmp_path), ["ts"], late="10 days"))
    assert "Scan parquet" in plan_text(once)
    assert hours(once, "ts") == [(10, 1), (10, 2), (11, 1), (12, 0)]


def test_no_file_of_the_stream_is_late(spark, tmp_path):
    """Later files hold earlier times, ids that are used again, nulls and pairs of other files."""
    parts = [[(1, 25, 1, "click"), (2, 26, 1, "click")], [(3, 27, 2, "view")], [(4, 1, 3, "click"), (5, 2, 1, "click")], [(1, 1, 4, "view"), (None, 2, None, None), (None, None, 5, None)]]
    for rows in parts:
        made = [(k, day and datetime(2024, 1, day), user, kind, 1.0, "{}") for k, day, user, kind in rows]
        spark.createDataFrame(made, contacts.EVENTS).coalesce(1).write.mode("append").parquet(str(tmp_path / "events.parquet"))
    kinds = ["user_id", "event_type"]
    by_file = contacts.event_stream(spark, str(tmp_path / "events.parquet")).select(*kinds)
    for done in (o_stream_dedup(spark, str(tmp_path)), contacts.run_to_end(contacts.without_repeats(by_file, kinds, late=None))):
        got = [tuple(r) for r in done.collect()]
        assert len(got) == len(set(got)) and set(got) == {(user, kind) for rows in parts for _, _, user, kind in rows}
