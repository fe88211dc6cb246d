"""Results kept up to date from a stream, in several batches, against those of one batch."""

import datetime as dt
from collections import Counter

import pyarrow as pa
import pyarrow.parquet as pq

from semigrid.streaming import events


def _write(folder, parts):
    start = dt.datetime(2024, 1, 1)
    rows = [(k, start + dt.timedelta(minutes=7 * k), k % 5, "abc"[k * k % 3], float(k), "{}") for k in range(60)]
    names = ["event_id", "ts", "user_id", "event_type", "value", "props"]
    for p in range(parts):
        table = pa.table({n: [r[c] for r in rows[p::parts]] for c, n in enumerate(names)})
        pq.write_table(table.set_column(1, "ts", table["ts"].cast(pa.timestamp("us", "UTC"))), f"{folder}/events-{p}.parquet")
    return rows


def test_product_from_batches(spark, tmp_path):
    count = Counter((u, e) for _, _, u, e, _, _ in _write(tmp_path, 3))
    want = Counter()
    for (u, e), n in count.items():
        for (w, f), m in count.items():
            if u == w:
                want[e, f] += n * m
    got = events.stream_product(events.event_stream(spark, str(tmp_path))).collect()
    assert {(r.i, r.j): r.v for r in got} == dict(want)


def test_degrees_from_batches(spark, tmp_path):
    rows = _write(tmp_path, 2)
    got = events.run_to_end(events.degrees(events.event_stream(spark, str(tmp_path))), "update").collect()
    last = {}
    for r in got:
        last[r.user_id] = max(r.degree, last.get(r.user_id, 0))
    assert last == dict(Counter(r[2] for r in rows))


def test_degrees_in_either_form(spark, tmp_path):
    rows = Counter(r[2] for r in _write(tmp_path, 3))
    stream = lambda: events.event_stream(spark, str(tmp_path))
    assert {r.user_id: r.degree for r in events.run_to_end(events.degrees(stream())).collect()} == dict(rows)
    last = events.run_to_end(events.degrees_by_state(stream()), "update").groupBy("user_id").max("degree").collect()
    assert {r[0]: r[1] for r in last} == dict(rows)


def test_late_events_are_left_out(spark, tmp_path):
    """An hour that the watermark has passed takes no more events, one within the hour of grace does."""
    day = dt.datetime(2024, 1, 1)
    names = ["event_id", "ts", "user_id", "event_type", "value", "props"]
    batches = [[(1, 9), (2, 12)], [(3, 13)], [(4, 9), (5, 12)]]  # (id, hour); the watermark stands at 12 when the third comes
    for k, batch in enumerate(batches):
        rows = [(i, day + dt.timedelta(hours=h, minutes=30), 7, "a", 0.0, "{}") for i, h in batch]
        table = pa.table({n: [r[c] for r in rows] for c, n in enumerate(names)})
        pq.write_table(table.set_column(1, "ts", table["ts"].cast(pa.timestamp("us", "UTC"))), f"{tmp_path}/events-{k}.parquet")
    stream = events.event_stream(spark, str(tmp_path))
    got = events.run_to_end(events.user_hours(stream), "update").groupBy("i", "j").max("v").collect()
    assert {r[1]: r[2] for r in got} == {9: 1, 12: 2, 13: 1}


def test_repeats_within_the_watermark(spark, tmp_path):
    _write(tmp_path, 2)
    for k in range(2):
        (tmp_path / f"events-{k + 2}.parquet").write_bytes((tmp_path / f"events-{k}.parquet").read_bytes())
    stream = events.without_repeats(events.event_stream(spark, str(tmp_path), 4), "1 day").select("event_id")
    assert sorted(r[0] for r in events.run_to_end(stream, "append").collect()) == list(range(60))


def test_no_events(spark, tmp_path):
    assert events.run_to_end(events.degrees(events.event_stream(spark, str(tmp_path)))).count() == 0
