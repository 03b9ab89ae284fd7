"""Queries that once made their data up read a given table through Spark."""

import pytest

from mts_search.plans import relational as R
from mts_search.plans import workloads as W

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize(("run", "table"), [(R.amortized_cost, "orders"), (R.tile_splits, "lineitem"), (W.walks_stats, "orders")])
def test_reads_its_table(spark, run, table):
    found = run(spark, SF)
    assert any(f.endswith(f"/{table}.parquet") for f in found.inputFiles()) and found.count() > 0


def test_supplier_chunks_take_one_shuffle_and_equal_those_of_points(spark, tmp_path):
    """Rows of a step are added up, price sums cut to thousands after that; other weeks, null days and null suppliers give zeros."""
    from mts_search.operators import fixtures as X
    from mts_search.operators.series import to_chunks

    rows = "select if(id % 41 = 40, null, id % 3) as l_suppkey, cast(id % 50 as double) as l_quantity, if(id % 7 = 0, null, id * 13.37D) as l_extendedprice, (id % 11) / 100.0D as l_discount, (id % 9) / 100.0D as l_tax"
    day = "if(id % 53 = 5, null, date_add(date'1994-12-01', cast(id * 7919 % 2600 as int))) as l_shipdate, 'A' as l_returnflag"
    spark.sql(f"{rows}, {day} from range(4000) union all select 9L, 1.0D, 1.0D, 0.0D, 0.0D, date'1990-01-01', 'A'").write.parquet(str(tmp_path / "lineitem.parquet"))
    for cumulative in (False, True):
        got = X.supplier_chunks(spark, str(tmp_path), 52, cumulative)
        want = to_chunks(X.supplier(spark, str(tmp_path), cumulative=cumulative), 52)
        known = {r["series_id"]: r["vals"] for r in want.collect()}
        found = {r["series_id"]: r["vals"] for r in got.collect()}
        assert set(found) == {0, 1, 2, 9, None} and not any(map(any, found[None])) and not any(map(any, found[9]))
        assert all(found[i] == known[i] for i in (0, 1, 2, 9))
    assert X.supplier_chunks(spark, str(tmp_path), 52)._jdf.queryExecution().executedPlan().toString().count("Exchange ") == 1


def test_many_channels_chunks_equal_those_of_points(spark, tmp_path):
    """Chunks straight from the rows: suppliers without rows of a flag are lines of zeros; null flags and days, other weeks."""
    from mts_search.operators import fixtures as X
    from mts_search.operators.series import to_chunks

    rows = "select if(id % 41 = 40, null, id * 31 % 13 + if(id % 2 = 0, 3, 1)) as l_suppkey, cast(id % 50 as double) as l_quantity, 1.0D as l_extendedprice, 0.0D as l_discount, 0.0D as l_tax"
    day = "if(id % 53 = 5, null, date_add(date'1994-12-01', cast(id * 7919 % 2600 as int))) as l_shipdate, element_at(array('A', 'N', 'R', null), cast(id % 4 + 1 as int)) as l_returnflag"
    spark.sql(f"{rows}, {day} from range(3000)").write.parquet(str(tmp_path / "lineitem.parquet"))
    d = str(tmp_path)
    want, got = to_chunks(X.many_channels(spark, d), 52), X.FIXTURES["many_channels"].chunks(spark, d, 52)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect())) and got.count() == 3
    assert not any(got.where("series_id = 0").first()["vals"][0]) and got.dtypes == want.dtypes


def test_queries_cut_from_chunks_equal_those_of_points(spark, monkeypatch):
    """One window of a chunk each, no point is made; channels that aren't there are left out. Hits and leaves make no frame from Python rows."""
    from mts_search.operators import fixtures as X
    from mts_search.operators import index as I
    from mts_search.operators.series import query_points, to_chunks

    p = X.supplier(spark, SF).where("series_id <= 40").persist()
    chunks = to_chunks(p, 52, 100).persist()
    for n, noise, channels, held_out in ((2, 1, None, False), (3, 16, [4, 0, 9], False), (2, 0, [1], True)):
        want, got = I.collect_queries(query_points(p, 52, n, noise, channels, held_out)), I.cut_queries(chunks, 52, n, noise, channels, held_out)
        assert [(a.query_id, a.channels, a.values.tolist()) for a in got] == [(b.query_id, b.channels, b.values.tolist()) for b in want] and len(got) == n
    monkeypatch.setattr(I, "KEPT_BYTES", 0)
    made, whole = [], type(spark).createDataFrame
    monkeypatch.setattr(type(spark), "createDataFrame", lambda self, data, *a, **k: made.append(type(data)) or whole(self, data, *a, **k))
    I.knn_index(I.build_index(chunks, 52), got, 3).count()
    assert made.count(list) == 1  # the queries, which are not read where the driver holds the leaves


def test_rows_of_a_series_are_shuffled_in_packed_blocks(spark):
    """A block adds up its rows and takes a few bytes a row; nothing else is shuffled."""
    import numpy as np
    import pyarrow as pa

    from mts_search.operators import fixtures as X
    from mts_search.operators import series as S

    g = np.random.default_rng(1)
    n, null = 50_000, np.arange(50_000) % 97 == 0
    s, t, v, w = g.integers(0, 60, n), g.integers(-3, 360, n), g.integers(-9, 9, n), g.integers(0, 1 << 40, n)
    rows = pa.table({"series_id": pa.array(s, mask=null), "t": pa.array(t), "c0": pa.array(v, mask=s == 5), "c1": pa.array(w)})
    dealt, found = S._dealt(rows, 357, 4), {}
    for block in dealt.column(1).to_pylist():
        for a, b, c, d in zip(*(x.tolist() for x in S.unpacked(block)), strict=True):
            assert (a, b) not in found
            found[a, b] = (c, d)
    want = {(S.NULL, 357): (0, 0)}
    for a, b, c, d, no in zip(s.tolist(), t.tolist(), v.tolist(), w.tolist(), null.tolist(), strict=True):
        key = (S.NULL, 357) if no else (a, b) if 0 <= b < 357 else (a, 357)
        x, y = want.get(key, (0, 0))
        want[key] = (x, y) if key[1] == 357 else (x + (0 if a == 5 else c), y + d)
    assert found == want and dealt.num_rows == 4 and sum(map(len, dealt.column(1).to_pylist())) < 12 * len(want)
    plan = X.supplier_chunks(spark, SF, 52)._jdf.queryExecution().optimizedPlan().toString()
    assert "block" in plan
    edge = [np.array([S.NULL, S.NULL, -5, 3, 1 << 62]), np.arange(5), np.array([1 << 40, -1, 0, 127, -128])]
    assert all((a == b).all() for a, b in zip(edge, S.unpacked(S.packed(edge)), strict=True))
