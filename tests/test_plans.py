import datetime
import decimal

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry_module
from rankfit import catalog
from rankfit.config import AcsConfig
from rankfit.plans import answers, build, exact, measures, rewrite, sqlhist
from rankfit.sources import io, workloads

DATA = "/root/testdata/sf0.001"


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_raw_rows_do_not_shuffle_and_scans_are_pruned(spark):
    rows = io.table(spark, DATA, "lineitem").where("l_quantity > 10")
    parts = build.partials(rows, "l_extendedprice", ["l_returnflag"])
    plan = plan_of(parts)
    assert "Exchange" not in plan and "MapInArrow" in plan
    assert "ReadSchema: struct<l_quantity:double,l_extendedprice:double,l_returnflag:string>" in plan and "GreaterThan(l_quantity,10.0)" in plan
    merged = plan_of(build.merge_summaries(parts, ["l_returnflag"]))
    assert merged.index("Exchange") < merged.index("MapInArrow")  # what is dealt out are the tasks' summaries
    asked = plan_of(sqlhist.rank_sql(sqlhist.node_slopes(sqlhist.equi_depth(rows, "l_extendedprice", 16)), rows.select(F.col("l_extendedprice").alias("x"))))
    assert "Broadcast" in asked and "Python" not in asked and "InArrow" not in asked


def test_partition_count_changes_no_exact_field(spark):
    rows = io.table(spark, DATA, "lineitem")
    found = {tuple(build.build_summary(rows.repartition(p), "l_extendedprice", levels=levels).select("n", "vmin", "vmax").first()) for p, levels in ((1, 1), (5, 1), (9, 2))}
    assert len(found) == 1


def test_odd_inputs(spark):
    schema = "g string, v double, w long, i long, d decimal(18,2), big decimal(38,10), day date, s string"
    row = lambda g, v, w=1: (g, v, w, (1 << 60) + 1, decimal.Decimal("1.25"), decimal.Decimal(1), datetime.date(2020, 1, 2), "x")
    df = spark.createDataFrame([row("a", 1.0), row("a", None), row("a", float("nan")), row(None, 2.0, 0), row(None, 3.0, 5), row("b", None)], schema)
    got = {r.g: r for r in build.build_summary(df, "v", ["g"], weight="w").collect()}
    assert (got["a"].n, got["a"].n_null, got["a"].n_nan) == (1, 1, 1) and (got[None].n, got[None].vmin) == (5, 3.0) and (got["b"].n, got["b"].vmin) == (0, None)
    assert build.build_summary(df.limit(0), "v").count() == 0
    assert build.build_summary(df, "i", cfg=AcsConfig(axis="i64")).first().imax == (1 << 60) + 1
    assert build.build_summary(df, "d", cfg=AcsConfig(axis="i64")).first().imin == 125
    assert build.build_summary(df, "day", cfg=AcsConfig(axis="i64")).first().imin == 18263
    for column, axis in (("big", "i64"), ("s", "f64"), ("v", "i64")):
        with pytest.raises(TypeError):
            build.build_summary(df, column, cfg=AcsConfig(axis=axis))


def test_many_groups_are_emitted_early(spark):
    df = spark.range(3000).select((F.col("id") % 300).alias("g"), F.rand(1).alias("v")).coalesce(2)
    parts = build.partials(df, "v", ["g"], task_bytes=2000)
    assert parts.count() >= 300
    whole = build.finish_summaries(build.merge_summaries(parts, ["g"]))
    assert whole.agg(F.sum("n"), F.count("*")).first() == (3000, 300)


def test_exact_side_equals_numpy(spark):
    df = spark.range(2000).select(F.round(F.randn(3), 1).alias("v")).repartition(5).cache()
    x = np.sort([r.v for r in df.collect()])
    ranks = {r.v: r["cum"] for r in exact.value_ranks(df, "v").collect()}
    assert all(ranks[v] == np.searchsorted(x, v, "right") for v in ranks)
    points = exact.query_points(df, "v", 37).orderBy("j").collect()
    assert [p.x for p in points] == [x[int(np.ceil(j * 2000 / 37)) - 1] for j in range(1, 38)]
    asked = spark.createDataFrame([(float(v),) for v in np.linspace(-5, 5, 41)], "x double")
    for few in (1000, 3):
        assert all(r.exact_rank == np.searchsorted(x, r.x, "right") for r in exact.exact_ranks(df, "v", asked, few=few).collect())
    assert exact.numbered(df, "v").agg(F.countDistinct("number"), F.max("number")).first() == (2000, 2000)


def test_answers_and_rewrites(spark):
    df = io.table(spark, DATA, "events")
    whole = build.build_summary(df, "value")
    grouped = build.build_summary(df, "value", ["event_type"])
    assert rewrite.rollup_summaries(grouped, [["event_type"], []], ["event_type"]).where("level = 1").first().n == whole.first().n
    assert measures.rank_error(whole, df, "value", 100).first().max_err < 0.01
    sized = build.resize_summaries(grouped, 20)
    assert sized.agg(F.max("buckets")).first()[0] <= 20
    assert answers.ks_distance(whole, whole).first().ks == 0
    assert answers.explode_buckets(plain := build.build_summary(df, "value", ["event_type"], cfg=AcsConfig(filter="none")), ["event_type"]).groupBy("event_type").agg(F.sum("cnt").alias("c")).join(plain, "event_type").where("abs(c - n) > 1e-6").count() == 0


@pytest.mark.parametrize("name", ["stream_rank_error_uniform", "merge_rank_error_bell", "ladder_merge_error", "selectivity_price_range", "percent_rank_estimates", "range_id_balance"])
def test_a_damaged_summary_fails_its_check(spark, monkeypatch, name):
    def flags():
        rows = catalog.QUERIES[name](spark, "/root/testdata/sf0.01")
        flag = [c for c, kind in rows.dtypes if kind == "boolean"][0]
        return {r[flag] for r in rows.select(flag).collect()}

    assert flags() == {True}

    original = build.map_summaries

    def damaged(df, change):
        def worse(state):
            out = change(state)
            if len(out.t) > 2:
                out.t = np.concatenate((out.t[:1], out.t[1:-1] + (out.t[-1] - out.t[0]) * 0.04, [out.t[-1] + (out.t[-1] - out.t[0]) * 0.05]))
            return out

        return original(df, worse)

    monkeypatch.setattr(build, "map_summaries", damaged)
    assert False in flags()


def test_functions_in_sql(spark):
    from rankfit.functions.register import register_functions

    register_functions(spark)
    build.build_summary(io.table(spark, DATA, "part"), "p_size").createOrReplaceTempView("sizes")
    row = spark.sql("select summary_n(summary) n, summary_bytes(summary) b, cdf_est(summary, 50D) c, rank_est(summary, 0D) z, summary_n(summary_merge(summary, summary)) m, summary_bytes(summary_resize(summary, 10)) r from sizes").first()
    assert row.n * 2 == row.m and row.c == 1 and row.z == 0 and row.r <= row.b
    assert spark.sql("select q.* from sizes, lateral acs_quantiles(summary, array(0.5D, 1D)) q").count() == 2
    assert spark.sql("select summary_n(acs_merge(summary)) n from sizes").first().n == row.n


def test_readers(spark, tmp_path):
    supplier = io.table(spark, DATA, "supplier")
    schema = "s_suppkey long, s_name string, s_nationkey int, s_acctbal double"
    for fmt in ("json", "orc", "csv"):
        supplier.write.format(fmt).save(f"{tmp_path}/{fmt}")
        assert io.read_any(spark, fmt, f"{tmp_path}/{fmt}", schema).count() == supplier.count()
    assert io.stream_rate(spark, 1).isStreaming
    dealt = io.range_ordered(supplier, "s_acctbal", 3).groupBy("part").agg(F.min("s_acctbal").alias("a"), F.max("s_acctbal").alias("b")).orderBy("part").collect()
    assert all(x.b <= y.a for x, y in zip(dealt, dealt[1:]))


def test_every_workload_and_one_experiment(spark):
    for name in workloads.WORKLOADS:
        rows = workloads.get(name)(spark, DATA)
        assert rows.columns == ["seq", "v"] and rows.limit(1).count() == 1
    found = measures.compare(workloads.get("power_like")(spark, DATA), ["acs", "compactor"], [400, 1600], chunks=4, m=100).toPandas()
    assert len(found) == 4 and (found["status"] == "ok").all() and measures.ratio(found, "acs", "compactor") > 1


def test_entry(spark):
    rows = entry_module.entry(spark).collect()
    assert len(rows) == 20 and all(r.within_eps for r in rows)
    assert set(entry_module.oracle_sql()) <= set(entry_module.queries())


@pytest.mark.parametrize("keys", [[], ["g"]])
@pytest.mark.parametrize("before", [0, 4])
def test_rolling_windows_hold_exactly_their_rows(spark, keys, before):
    rows = [(g, t, float(t * 10 + i)) for g in "ab" for t in range(150 if g == "a" else 3) for i in range(1 + t % 3)]
    if not keys:
        rows = [r for r in rows if r[0] == "a"]
    df = spark.createDataFrame(rows, "g string, t int, v double")
    got = rewrite.rolling_summaries(build.build_summary(df, "v", [*keys, "t"]), "t", before, keys).collect()
    assert len(got) == len({r[:2] for r in rows})
    for r in got:
        own = [v for g, t, v in rows if r.t - before <= t <= r.t and (not keys or g == r.g)]
        assert (r.n, r.vmin, r.vmax) == (len(own), min(own), max(own))


def test_small_group_ranks_stay_exact_where_groups_are_large_or_have_nulls(spark, tmp_path):
    rows = [("en", "a", (i * i) % 9973) for i in range(3000)] + [("de", "b", i % 7) for i in range(200)] + [(None, "a", 5), ("en", None, 5), ("de", "b", None)]
    docs = spark.createDataFrame(rows, "lang string, source string, n_chars long")
    docs.repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    got = {(r.lang, r.source, r.x): r.est_rank for r in catalog.QUERIES["small_group_exact_ranks"](spark, str(tmp_path)).collect()}
    want = {(g, s, float(n)): sum(1 for a, b, c in rows if (a, b) == (g, s) and c is not None and c <= n) for g, s, n in set(rows) if None not in (g, s, n)}
    assert got == want
