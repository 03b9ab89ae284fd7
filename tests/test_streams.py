"""Streams over files that are written in another order than they are to be played in."""

import pytest

from mts_search.streaming import streams as S


@pytest.fixture
def late(spark, tmp_path):
    """Events whose first rows are the longest by far, so that the task of the first file ends last."""
    ts = "timestamp'2024-01-01' + make_dt_interval(id div 2 * 2, 0, 30 * (id % 2))"
    rows = spark.range(40, numPartitions=1).selectExpr("id as event_id", f"{ts} as ts", "1L as user_id", "if(id % 2 = 0, 'click', 'purchase') as event_type", "1.0D as value", "repeat(sha(string(id)), if(id < 4, 1200000, 1)) as props")
    rows.write.parquet(str(tmp_path / "events.parquet"))
    return str(tmp_path)


def test_dedup_of_first_file_written_last(spark, late):
    assert sorted(r[0] for r in S.stream_dedup(spark, late).collect()) == list(range(40))


def test_pairs_of_first_file_written_last(spark, late):
    assert sorted(tuple(r) for r in S.stream_pairs(spark, late).collect()) == [(i, i + 1) for i in range(0, 40, 2)]


def test_sessions_of_first_file_written_last(spark, late):
    assert sorted((r["start_s"], r["n"]) for r in S.stream_sessions(spark, late).collect()) == [(1704067200 + 86400 * i, 2) for i in range(0, 40, 2)]


def test_row_exactly_a_gap_later_begins_a_session(spark, tmp_path):
    rows = "select id as event_id, timestamp'2024-01-01' + make_dt_interval(0, 0, 0, s) as ts, 1L as user_id, 'view' as event_type, 1.0D as value, '' as props"
    spark.createDataFrame([(0, 0.0), (1, 21600.0), (2, 43199.999999)], "id bigint, s double").selectExpr("id", "cast(s as decimal(18, 6)) as s").createOrReplaceTempView("steps")
    spark.sql(f"{rows} from steps").write.parquet(str(tmp_path / "events.parquet"))
    assert sorted((r["start_s"], r["n"]) for r in S.stream_sessions(spark, str(tmp_path)).collect()) == [(1704067200, 1), (1704088800, 2)]


def test_pairs_are_keyed_by_stretches_of_the_span(spark, tmp_path):
    """Rows at a stretch's borders, exactly the span later and a microsecond beyond; a long history is no part of a key's state."""
    rows = [(0, 3599.999999, "click"), (1, 3600.0, "purchase"), (2, 7199.999999, "purchase"), (3, 7200.0, "purchase"), (4, 10800.0, "click"), (5, 10800.0, "purchase"), (6, 14400.0, "purchase"), (7, 14400.000001, "purchase")]
    spark.createDataFrame(rows, "id bigint, s double, kind string").selectExpr("id as event_id", "timestamp'2024-01-01' + make_dt_interval(0, 0, 0, cast(s as decimal(18, 6))) as ts", "1L as user_id", "kind as event_type", "1.0D as value", "'' as props").write.parquet(str(tmp_path / "events.parquet"))
    assert sorted(tuple(r) for r in S.stream_pairs(spark, str(tmp_path)).collect()) == [(0, 1), (0, 2), (4, 5), (4, 6)]
    e = spark.read.parquet(str(tmp_path / "events.parquet"))
    plan = S.pairs_within(e, e)._jdf.queryExecution().optimizedPlan().toString()
    assert "(k1#" in plan and "= k2#" in plan
