"""Operators of the study keys over all series, windows and vectors, against numpy."""

from datetime import date, timedelta

import numpy as np
import pytest

from mts_search.plans import relational as R

IDS, M = (1, 11, 25), 70  # ids beyond any prefix, 19 starts each


@pytest.fixture
def series(spark, monkeypatch):
    g = np.random.default_rng(5)
    x = {(i, c): g.integers(0, 90, M) for i in IDS for c in (0, 1)}
    df = spark.createDataFrame([(i, c, t, int(v)) for (i, c), a in x.items() for t, v in enumerate(a)], "series_id bigint, channel int, t bigint, v bigint").persist()
    monkeypatch.setattr(R, "sw", lambda spark, d: df)
    return x


def spectra(x, c):
    w = {(i, s): np.fft.rfft(x[i, c][s : s + R.Q]) for i in IDS for s in range(M - R.Q + 1)}
    weight = np.full(R.Q // 2 + 1, 2.0)
    weight[[0, -1]] = 1
    return w, weight


def test_spectra_of_all_series(spark, series):
    w, weight = spectra(series, 0)
    got = {(r["series_id"], r["start"], r["bin"]): (r["re"], r["im"]) for r in R.sliding_dft(spark, "").collect()}
    assert set(got) == {(*k, b) for k in w for b in (1, 2, 3)}
    assert all(abs(complex(*v) - w[i, s][b]) < 2e-3 for (i, s, b), v in got.items())
    energy = {(r["channel"], r["bin"]): r["share"] for r in R.energy_by_bin(spark, "").collect()}
    ardc = {(r["channel"], r["bin"]): r["share"] for r in R.ardc_by_bin(spark, "").collect()}
    for c in (0, 1):
        w, weight = spectra(series, c)
        e = np.array([weight * abs(f) ** 2 for f in w.values()])
        assert [energy[c, b] for b in range(27)] == pytest.approx((e / e.sum(1, keepdims=True)).mean(0), abs=1e-5)
        keys = list(w)
        pairs = np.array([weight * abs(w[a] - w[b]) ** 2 for n, a in enumerate(keys) for b in keys[n + 1 :]])
        assert [ardc[c, b] for b in range(27)] == pytest.approx((pairs / pairs.sum(1, keepdims=True)).mean(0), abs=1e-5)


def test_bounds_of_pairs(spark, series):
    at = {i * 1000 + s: series[i, 0][s : s + R.Q] for i in IDS for s in range(M - R.Q + 1)}
    for pivot in (False, True):
        rows = R._bound_pairs(spark, "", pivot).collect()
        assert len(rows) == len(at) * (len(at) - 1) // 2
        assert all(abs(r["d2"] - ((at[r["i"]] - at[r["k"]]) ** 2).sum()) < 1e-2 and r["lb2"] <= r["d2"] + 1e-2 for r in rows)


def test_sample_reaches_all_series(spark):
    p = spark.range(40).selectExpr("id + 1 as series_id").crossJoin(spark.range(357).selectExpr("id as t"))
    got = R._sample(p).collect()
    assert len(got) == R.SAMPLE and any(r["series_id"] > 5 for r in got) and any(r["start"] % R.Q for r in got) and max(r["start"] for r in got) > 260


def test_tiles_runs_and_trend_of_all_series(spark, series, tmp_path):
    tiles = R.ntile_tiles(spark, "").collect()
    assert {r["series_id"] for r in tiles} == set(IDS) and len(tiles) == len(IDS) * (M - R.Q + 1)
    runs = R.islands_runs(spark, "").collect()
    assert sum(r["n_windows"] for r in runs) == len(tiles) == R.compression_stats(spark, "").first()["windows"]
    trend = {(r["series_id"], r["channel"]): r["path"] for r in R.lag_lead_trend(spark, "").collect()}
    assert trend == {k: abs(np.diff(a)).sum() for k, a in series.items()}
    spark.createDataFrame([(1, 7), (2, 3)], "c_custkey bigint, c_nationkey int").write.parquet(str(tmp_path / "customer.parquet"))
    weeks = [0, 20, 40, 69, 70]
    days = [(k, 1, date(1995, 1, 2) + timedelta(days=7 * w)) for k, w in enumerate(weeks)] + [(99, 2, date(1995, 1, 2))]
    spark.createDataFrame(days, "o_orderkey bigint, o_custkey bigint, o_orderdate date").write.parquet(str(tmp_path / "orders.parquet"))
    want = {k: sum(r["first_start"] <= w <= r["last_start"] + R.Q - 1 for r in runs) for k, w in enumerate(weeks)}
    assert {r["o_orderkey"]: r["n_runs"] for r in R.interval_join_windows(spark, str(tmp_path)).collect()} == {k: n for k, n in want.items() if n}


def test_distances_of_all_vectors(spark, tmp_path):
    e = np.random.default_rng(6).normal(size=(60, 4))
    spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(e)], "vec_id bigint, embedding array<float>").write.parquet(str(tmp_path / "embeddings.parquet"))
    got = {r["vec_id"]: r["distance"] for r in R.array_distance(spark, str(tmp_path)).collect()}
    assert [got[i] for i in range(60)] == pytest.approx(np.linalg.norm(e - e[0], axis=1), abs=1e-3)
