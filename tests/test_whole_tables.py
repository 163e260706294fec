"""Queries over whole tables against their SQL twins, and streams with late events."""

import datetime as dt
from collections import Counter

import pyarrow as pa
import pyarrow.parquet as pq
import pytest

from tests.conftest import SMALL
from twigrank import catalog
from twigrank.streaming import streams

CHOICE = ["join_inner", "join_left_anti", "join_full", "components", "join_range", "khop_2", "sink_roundtrip_csv", "sink_roundtrip_json", "sink_roundtrip_orc", "sink_roundtrip_parquet", "stream_static_join", "stream_tumbling", "stream_sliding", "stream_dedup", "stream_interval_join", "stream_index_merge", "stream_topk", "stream_session", "stream_complete_totals"]


@pytest.mark.parametrize("name", CHOICE)
def test_equals_sql(spark, duck, name):
    mine, theirs = catalog.queries()[name](spark, SMALL).toPandas(), duck.sql(catalog.oracle_sql()[name]).df()
    cols = sorted(theirs.columns)
    assert sorted(mine.columns) == cols and len(theirs)
    rows = lambda df: sorted(tuple(map(str, r)) for r in df[cols].itertuples(index=False, name=None))
    assert rows(mine) == rows(theirs)


@pytest.fixture(scope="module")
def sixty_days(spark, tmp_path_factory):
    """An event an hour on sixty days, and a view of the same user five minutes before it."""
    start, path = dt.datetime(2024, 1, 1), tmp_path_factory.mktemp("late")
    rows = [(2 * h + k, start + dt.timedelta(hours=h, minutes=30 + 5 * k), h % 7, ("view", "purchase")[k], 1.5, "{}") for h in range(60 * 24) for k in (0, 1)]
    names = ["event_id", "ts", "user_id", "event_type", "value", "props"]
    pq.write_table(pa.table({n: [r[i] for r in rows] for i, n in enumerate(names)}, schema=None).cast(pa.schema([("event_id", pa.int64()), ("ts", pa.timestamp("us")), ("user_id", pa.int64()), ("event_type", pa.string()), ("value", pa.float64()), ("props", pa.string())])), path / "events.parquet")
    return str(path), rows


def test_every_day_of_arrival_is_streamed(spark, sixty_days):
    path, rows = sixty_days
    got = streams.stream_static_join(spark, path).collect()
    assert sorted(r["event_id"] for r in got) == [r[0] for r in rows]


def test_late_events_count_in_open_windows(spark, sixty_days):
    """Against the watermark by hand: batches of eight files, each a day of arrival; a batch emits the windows that the
    watermark of the batches before it has passed, after its own rows, and later batches drop rows of these."""
    path, rows = sixty_days
    hour = lambda ts: ts.replace(minute=0)
    batches: dict[int, list] = {}
    for r in rows:
        day = (r[1].date() - dt.date(2024, 1, 1)).days + (2 if r[0] % 20 == 0 else 0)
        batches.setdefault(day // 8, []).append(r)
    want, emitted, mark, high = Counter(), dt.datetime.min, dt.datetime.min, dt.datetime.min
    for b in sorted(batches):
        want.update(hour(r[1]) for r in batches[b] if hour(r[1]) + dt.timedelta(hours=1) > emitted)
        emitted = mark
        high = max([high, *(r[1] for r in batches[b])])
        mark = high - dt.timedelta(days=1)
    want = {h: n for h, n in want.items() if h + dt.timedelta(hours=1) <= mark}
    late = [r for r in rows if r[0] % 20 == 0]
    got = {r["start"]: r["n"] for r in streams.stream_tumbling(spark, path).collect()}
    assert got == want
    assert any(want.get(hour(r[1])) == 2 for r in late)
