"""The worked example, laws and bounds of the methods, boundaries, and equality with exact answers and SQL."""

import math
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from setoverlap.functions.hashing import unit_hash
from setoverlap.operators import allpairs, cardinality, exact, mle, pairstats, registers, schemes, simulate, theory
from setoverlap.plans import experiments, registry, relational, texts, workloads


def sides(spark, a, b):
    rows = [(x, True, False) for x in a] + [(x, False, True) for x in b]
    return spark.createDataFrame(rows, "e string, in_a boolean, in_b boolean")


def fit(spark, a, b, m=512, **kw):
    return mle.mle_intersection(workloads.stats_of(sides(spark, a, b), m=m, **kw)).first()


def test_worked_example(spark):
    got = exact.exact_sizes(sides(spark, "abcdab", "aacc"), "e", F.col("in_a"), F.col("in_b")).first()
    assert (got.card_a, got.card_b, got.card_both, got.card_any) == (4, 2, 2, 4)
    est = fit(spark, "abcdab", "aacc")
    assert est.boundary == "b_inside" and est.card_both == est.card_b


@pytest.mark.parametrize("a,b,kind", [("abc", "xyz", "disjoint"), ("abc", "cba", "identical"), ("ab", "abcdef", "a_inside"), ("abc", "", "b_empty"), ("", "abc", "a_empty")])
def test_boundaries(spark, a, b, kind):
    est = fit(spark, a, b)
    assert est.boundary == kind
    for x in (est.card_a, est.card_b, est.card_both):
        assert math.isfinite(x)
    assert abs(est.card_a - len(a)) < 0.6 + len(a) * 0.2 and abs(est.card_both - len(set(a) & set(b))) < 0.8


def test_md5_check_value(spark):
    assert spark.range(1).select(unit_hash(F.lit(5), F.lit(1), "md5").alias("v")).first().v == 973602861767128816


def test_duplicates_order_and_partitions_do_not_matter(spark):
    ids = spark.range(300).selectExpr("cast(id % 97 as string) e")
    rows = lambda d: sorted(map(tuple, registers.build_registers(d, "e", m=32).collect()))
    assert rows(ids) == rows(ids.unionAll(ids).repartition(7)) == rows(ids.distinct())


def test_union_of_registers_is_registers_of_union(spark):
    df = spark.range(500).selectExpr("id % 3 g", "id e")
    regs = registers.build_registers(df, "e", ["g"], 16)
    assert sorted(map(tuple, registers.merge_registers(regs).collect())) == sorted(map(tuple, registers.build_registers(df, "e", m=16).collect()))
    packed = {r.g: r.regs for r in registers.pack(regs, ["g"]).collect()}
    assert len(packed) == 3 and all(len(x) == 16 for x in packed.values())


def test_score_is_slope_of_log_likelihood(spark):
    st = spark.createDataFrame([(100, 40, 35, 25, 35, 25, 0.9, 1.1, 0.6, 1.0)], "m long, k_tie long, k_b long, k_a long, k_b_seen long, k_a_seen long, sum_a double, sum_b double, sum_any double, scale double")
    ll = lambda a, b, n: st.select(mle.log_likelihood(F.lit(a), F.lit(b), F.lit(n)).alias("x")).first().x
    g = st.select(mle.score(F.lit(110.0), F.lit(95.0), F.lit(60.0)).alias("g")).first().g
    h = 1e-4
    assert g.g_n == pytest.approx((ll(110.0, 95.0, 60 + h) - ll(110.0, 95.0, 60 - h)) / 2 / h, rel=1e-5)
    est = mle.mle_intersection(st).first()
    best = ll(est.card_a, est.card_b, est.card_both)
    assert est.converged and est.iters <= 10
    assert all(best >= ll(est.card_a * x, est.card_b * y, est.card_both * z) for x, y, z in ((1.01, 1, 1), (1, 0.99, 1), (1, 1, 1.01), (1, 1, 0.99)))


def test_theory(spark):
    one = spark.range(1)
    val = lambda c: one.select(c.alias("x")).first().x
    L = F.lit  # noqa: N806
    a, m = L(1e6), L(1000.0)
    for v in (theory.crb_intersection(a, a, a, m), theory.var_scheme1(a, a, a, m), theory.var_scheme2(a, a, a, m), theory.var_scheme3(a, a, a, m), theory.var_scheme3(a, a, a, m, "lemma")):
        assert val(v * m / a / a) == pytest.approx(1.0, rel=1e-9)
    n, b = L(5e5), L(1e6)
    norm = lambda v: val(v * m / n / n)
    assert norm(theory.crb_intersection(a, b, n, m)) == pytest.approx(2.143, abs=1e-3)
    assert norm(theory.crb_from_fisher(a, b, n, m)) == pytest.approx(norm(theory.crb_intersection(a, b, n, m)))
    assert norm(theory.var_scheme1(a, b, n, m, "printed")) == pytest.approx(5.190, abs=1e-3)
    assert norm(theory.var_scheme3(a, b, n, m, "printed")) == pytest.approx(2.792, abs=1e-3)
    assert norm(theory.var_scheme3(a, b, n, m, "shared")) == pytest.approx(2.292, abs=1e-3)
    p = val(theory.case_probabilities(a, b, n))
    assert p.p_tie + p.p_a + p.p_b == pytest.approx(1)


def test_beta_identities():
    assert theory.beta_cdf(0.3, 1, 1) == pytest.approx(0.3, abs=1e-6)
    assert theory.beta_cdf(0.4, 5, 1) == pytest.approx(0.4**5, rel=1e-4)
    assert theory.beta_cdf(0.4, 2, 3) == pytest.approx(1 - theory.beta_cdf(0.6, 3, 2), abs=1e-4)


def test_simulated_variance_meets_bound_and_schemes(spark):
    acc = experiments.simulated_accuracy(spark, (1.0, 5.0), [0.5], (1000,), 4000, 5)
    got = {(r.size_ratio, r.scheme): r for r in acc.collect()}
    want = {(1.0, "ml"): 2.143, (1.0, "inclusion_exclusion"): 3.667, (1.0, "jaccard_union"): 3.0, (1.0, "jaccard_sum"): 2.292, (5.0, "ml"): 6.465, (5.0, "jaccard_sum"): 9.539}
    for k, v in want.items():
        assert got[k].var_norm * 1000 == pytest.approx(v, rel=0.12)
        assert got[k].bias_norm < 0.002 + 4 * math.sqrt(v / 1000 / 4000)
    assert got[(1.0, "ml")].mse == pytest.approx(got[(1.0, "ml")].var_raw, rel=0.05)


def test_newton_converges_in_few_steps(spark):
    grid = simulate.experiment_grid(spark, (1.0, 5.0, 10.0), [0.1, 0.5, 0.9], (1000,))
    st = simulate.simulate_stats(grid, 50)
    full = mle.mle_intersection(st).select("cell", "trial", F.col("card_both").alias("n"), "iters", "boundary")
    four = mle.mle_intersection(st, iters=4, tol=0.0).select("cell", "trial", F.col("card_both").alias("n4"))
    worst = full.join(four, ["cell", "trial"]).where("boundary is null").agg(F.max(F.abs(F.col("n4") / F.col("n") - 1)).alias("e"), F.max("iters").alias("i")).first()
    assert worst.e < 1e-4 and worst.i <= 10


def test_bucketed_layout_and_arrow_engine_near_truth(spark):
    df = spark.range(3000).select(F.col("id").alias("e"), (F.col("id") < 2000).alias("in_a"), (F.col("id") >= 1000).alias("in_b"))
    for m in (512, 2048):
        st = workloads.stats_of(df, m=m, family="xxhash64", layout="bucketed")
        est = mle.mle_intersection(st).first()
        assert est.card_both == pytest.approx(1000, rel=0.25) and est.card_a == pytest.approx(2000, rel=0.2)
    from setoverlap.functions.hashing import register_energy

    regs = registers.build_registers(df, "e", m=512, engine="arrow")
    assert regs.agg(cardinality.card_from_registers(F.sum(register_energy(F.col("v"))), F.lit(512)).alias("c")).first().c == pytest.approx(3000, rel=0.2)


def test_log_log_rank_base(spark):
    df = spark.range(20000)
    est = [cardinality.hll_estimate(cardinality.hll_registers(df, "id", m=512, rank_base=b), [], 512).first().card_hll / 20000 for b in (1, 0)]
    assert est[0] == pytest.approx(1, abs=0.15) and est[1] == pytest.approx(0.5, abs=0.08)
    assert cardinality.hll_alpha(512) == pytest.approx(0.71975, abs=2e-4)


def test_estimates_within_four_standard_errors(spark, sf):
    for src, exact_n in ((workloads.customers_by_year, 91), (workloads.customers_by_status, 143)):
        est = mle.estimate_interval(mle.mle_intersection(workloads.stats_of(src(spark, sf), m=1024, family="xxhash64"))).first()
        assert abs(est.card_both - exact_n) <= 4 * est.std_err + 1


def test_plan_has_two_exchanges_and_no_python(spark, sf):
    est = mle.mle_intersection(workloads.stats_of(workloads.customers_by_year(spark, sf)))
    plan = est._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 2 and "Python" not in plan and "Arrow" not in plan
    assert "o_totalprice" not in plan


def test_clip_and_side_by_side(spark, sf):
    st = schemes.with_cardinalities(workloads.stats_of(workloads.customers_by_year(spark, sf)))
    r = st.select(schemes.scheme_incl_excl(True).alias("n"), "c_a").first()
    assert 0 <= r.n <= r.c_a
    assert schemes.estimate_all(st).count() == 4


def test_naive_refuses_large(spark):
    with pytest.raises(ValueError):
        exact.exact_intersection_naive(spark.range(20000), spark.range(10))


def test_registry_has_sql_for_known_names():
    assert set(registry.oracle_sql()) <= set(registry.queries()) and registry.FLAGSHIP in registry.queries()


def test_store_as_of(spark, tmp_path):
    from setoverlap.sources.tables import load_registers, save_registers

    regs = registers.build_registers(spark.range(10), "id", m=4)
    for day in ("2024-01-01", "2024-01-03"):
        save_registers(regs, str(tmp_path / "store"), "ids", day)
    assert load_registers(spark, str(tmp_path / "store"), "ids", "2024-01-02").count() == 4
    assert load_registers(spark, str(tmp_path / "store"), "ids").count() == 8


def test_streaming_merges_like_batch(spark, sf, tmp_path):
    from setoverlap.streaming import windows

    q = windows.running_registers(windows.read_events(spark, sf), "user_id", "event_type", 8, str(tmp_path / "regs"), str(tmp_path / "cp"))
    q.awaitTermination()
    got = registers.merge_registers(spark.read.parquet(str(tmp_path / "regs")), ["event_type"])
    want = registers.build_registers(spark.read.parquet(f"{sf}/events.parquet"), "user_id", ["event_type"], 8)
    assert sorted(map(tuple, got.select("event_type", "k", "v").collect())) == sorted(map(tuple, want.collect()))
    assert pairstats.pair_stats_all(got, "event_type", 8).count() == 10


def test_figures_run_the_whole_experiment():
    assert experiments.TRIALS == 10_000 and experiments.STEPS == [i / 100 for i in range(101)]


def test_document_bands_find_pairs_at_their_threshold(spark):
    # 200 pairs of 60 elements at Jaccard 0.5 (40 shared of 80)
    sets = spark.range(400).selectExpr("id as doc_id", "explode(transform(sequence(0, 59), i -> cast(div(id, 2) * 1000 + if(i < 40, i, i + 100 * (id % 2)) as string))) as e")
    regs = registers.build_registers(sets, "e", ["doc_id"], 64)
    want = allpairs.exact_pair_overlaps(sets, "doc_id", "e").where("2 * card_both >= card_any")
    found = want.join(allpairs.band_candidates(regs, "doc_id", texts.BAND), ["x", "y"])
    assert want.count() == 200 and found.count() >= 198


def test_running_union_has_every_register_and_supplier_pairs_are_exact(spark, sf):
    got = registry.registers_running_union(spark, sf).collect()
    assert {r.k for r in got} == set(range(8))
    parts = {}
    for r in registry.load_table(spark, sf, "lineitem").select("l_suppkey", "l_partkey").collect():
        parts.setdefault(r.l_suppkey, set()).add(r.l_partkey)
    want = sorted((-len(parts[x] & parts[y]), x, y) for x in parts for y in parts if x < y and parts[x] & parts[y])[:20]
    assert [(-r.card_both, r.x, r.y) for r in relational.supplier_pairs_top20_exact(spark, sf).collect()] == want


def test_arrow_engine_gives_the_same_registers(spark):
    from setoverlap.functions.hashing import mixed_long, slot_seeds, unit_hash
    import numpy as np

    df = spark.createDataFrame([(g, e) for g in ("a", None) for e in [*map(str, range(500)), "", None, "\u00e9"]], "g string, e string")
    for layout in ("k_hash", "bucketed"):
        sql, arrow = (sorted(map(str, registers.build_registers(df, "e", ["g"], 64, layout=layout, engine=x).collect())) for x in ("sql", "arrow"))
        assert sql == arrow and len(sql) > 100
    with pytest.raises(ValueError):
        registers.build_registers(df, "e", engine="arrow", family="md5")
    got = spark.range(1).select(F.xxhash64(F.lit(7).cast("long"), F.lit(-3).cast("long")).alias("h")).first().h
    assert int(mixed_long(np.array([-3], np.int64).view(np.uint64), slot_seeds(8)[7]).view(np.int64)[0]) == got
    with pytest.raises(ValueError):
        unit_hash(F.lit(1), F.lit(1), "crc32")


def test_packed_statistics_equal_those_by_register(spark):
    df = spark.range(900).selectExpr("id % 3 g", "id - id % 2 * (id % 3) * 7 e")
    for layout in ("k_hash", "bucketed"):
        regs = registers.build_registers(df, "e", ["g"], 512, layout=layout)
        got = {(r.x, r.y): r for r in pairstats.pair_stats_all(regs, "g", 512, layout=layout).collect()}
        assert set(got) == {(0, 1), (0, 2), (1, 2)}
        for (x, y), r in got.items():
            both = df.where(F.col("g").isin(x, y)).select("e", (F.col("g") == x).alias("in_a"), (F.col("g") == y).alias("in_b"))
            want = workloads.stats_of(both, m=512, family="xxhash64", layout=layout).first()
            for c in ("m", "k_tie", "k_b", "k_a", "k_b_seen", "k_a_seen"):
                assert r[c] == want[c]
            for c in ("sum_a", "sum_b", "sum_any", "scale"):
                assert r[c] == pytest.approx(want[c], rel=1e-9)
    with pytest.raises(ValueError):
        pairstats.pair_stats_all(regs, "g", 512, most_groups=2)


def test_pairs_within_hot_keys_and_joins_back(spark, monkeypatch):
    from setoverlap.operators import skew

    monkeypatch.setattr(skew, "BLOCK", 8)
    rows = spark.range(100).selectExpr("if(id < 60, 0, id) as k", "id as x").unionByName(spark.createDataFrame([(70, 71), (0, 3)], "k long, x long"))
    got = [tuple(r) for r in skew.pairs_within(rows.distinct(), ["k"], "x").collect()]
    want = {(0, a, b) for a in range(60) for b in range(a + 1, 60)} | {(70, 70, 71)}
    assert set(got) == want and len(got) == len(want)
    stats = rows.groupBy("k").agg(F.count("*").alias("n"))
    assert skew.join_back(rows, stats, ["k"], "x", "n").count() == rows.count()


def test_exact_similar_pairs_equal_brute_force(spark):
    import random

    r = random.Random(4)
    sets = {i: set(r.sample(range(60), r.randint(1, 30))) for i in range(40)}
    sets |= {100 + i: set(sets[i]) for i in range(5)} | {200 + i: (sets[i] - {min(sets[i])}) | {900 + i} for i in range(20)}
    df = spark.createDataFrame([(i, str(e)) for i, s in sets.items() for e in s], "g long, e string")
    got = {tuple(x) for x in allpairs.exact_similar_pairs(df, "g", "e", 1, 2).collect()}
    first = {i: min(j for j in sets if sets[j] == sets[i]) for i in sets}
    want = {(x, y, len(sets[x] & sets[y]), len(sets[x] | sets[y])) for x in sets for y in sets if x < y and first[x] == x and first[y] == y and 2 * len(sets[x] & sets[y]) >= len(sets[x] | sets[y])}
    assert got == want | {(first[i], i, len(sets[i]), len(sets[i])) for i in sets if first[i] != i}


def test_array_fit_covers_boundaries(spark):
    rows = [("abc", "xyz"), ("abc", "cba"), ("ab", "abcdef"), ("abcdef", "ab"), ("abc", ""), ("", "abc"), ("abcdab", "aacc"), ("abcdefgh", "efghijkl")]
    for a, b in rows:
        st = workloads.stats_of(sides(spark, a, b), m=256, family="xxhash64")
        x, y = mle.mle_intersection(st).first(), mle.mle_intersection(st, engine="arrow").first()
        assert (x.boundary, x.converged) == (y.boundary, y.converged)
        for c in ("card_a", "card_b", "card_both", "var_hat"):
            assert x[c] == pytest.approx(y[c], rel=1e-9, abs=1e-12)


def test_readers_and_register_kinds(spark, tmp_path):
    from setoverlap.sources.tables import load_file, load_registers, save_registers

    df = spark.createDataFrame([(1, "a"), (2, "b")], "id int, t string")
    for kind in ("csv", "json", "orc", "parquet"):
        path = str(tmp_path / kind)
        (df.write.option("header", True) if kind == "csv" else df.write).format(kind).save(path)
        assert sorted(map(tuple, load_file(spark, path, kind, df.schema).collect())) == [(1, "a"), (2, "b")]
    df.select("t").write.text(str(tmp_path / "text"))
    assert load_file(spark, str(tmp_path / "text"), "text").count() == 2
    regs = registers.build_registers(spark.range(10), "id", m=4)
    store = str(tmp_path / "kinds")
    save_registers(regs, store, "ids", "2024-01-01")
    save_registers(registers.build_registers(spark.range(10), "id", m=4, family="md5"), store, "ids", "2024-01-01", "md5-0-k_hash")
    assert sorted(map(tuple, load_registers(spark, store, "ids").select("k", "v").collect())) == sorted(map(tuple, regs.collect()))


def test_every_query_without_sql_is_known():
    points = {"accuracy_controlled", "improvement_controlled", "fig1_bias", "fig2_variance", "fig3_improvement", "doc_near_duplicates_ml", "doc_sketch_classes", "doc_banding_candidates", "registers_arrow_customers"}
    assert set(registry.queries()) - set(registry.oracle_sql()) == points  # each has a query beside it that SQL or this file holds


def copied(spark, sf, folder, shifts):
    """Tables of sf repeated under a folder: {table: {column: shift a copy}}; returns the folder and its copies' count."""
    copies = 6
    for table, columns in shifts.items():
        one = spark.read.parquet(f"{sf}/{table}.parquet")
        many = one.crossJoin(spark.range(copies).toDF("copy_"))
        many = many.withColumns({c: (F.col(c) + F.col("copy_") * by).cast(one.schema[c].dataType) for c, by in columns.items()}).drop("copy_")
        many.coalesce(1).write.parquet(f"{folder}/{table}.parquet")
    return str(folder)


def by_sql(name, folder, *tables):
    """Rows of a query's SQL over the tables of a folder."""
    import duckdb

    con = duckdb.connect()
    for t in tables:
        path = f"{folder}/{t}.parquet"
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{path if Path(path).is_file() else path + '/*.parquet'}')")
    return con.sql(registry.oracle_sql()[name]).fetchall()


def test_linear_counting_of_more_suppliers_than_buckets(spark, tmp_path):
    for n in (400, 3000, 20_000):  # empties left, raw estimate above 2.5 m, no bucket empty
        folder = tmp_path / str(n)
        spark.range(1, n + 1).toDF("s_suppkey").coalesce(1).write.parquet(f"{folder}/supplier.parquet")
        assert [tuple(r) for r in registry.queries()["hll_linear_small"](spark, str(folder)).collect()] == by_sql("hll_linear_small", folder, "supplier")


def test_supplier_pairs_of_more_groups_than_may_be_crossed(spark, tmp_path):
    rows = {"many": "2100 * 4, id % 2100, (id * 7919 + id div 2100) % 1500", "few_tied": "60 * 3, id % 60, if(id in (7, 67, 60), 500, id)"}
    for kind, text in rows.items():  # more than MOST_GROUPS suppliers; fewer than 20 pairs that tie at all
        n, supplier, part = text.split(", ", 2)
        folder = tmp_path / kind
        spark.range(eval(n)).selectExpr(f"cast({part} as bigint) l_partkey", f"cast({supplier} as bigint) l_suppkey").coalesce(1).write.parquet(f"{folder}/lineitem.parquet")
        got = [tuple(r) for r in registry.queries()["ml_supplier_pairs_top20"](spark, str(folder)).collect()]
        assert got == by_sql("ml_supplier_pairs_top20", folder, "lineitem") and len(got) == 20


def test_sliding_windows_hash_a_row_once_and_batches_are_read_by_many_tasks(spark, tmp_path, monkeypatch):
    import pyarrow.parquet as pq

    from setoverlap.plans import streams
    from setoverlap.streaming import windows

    ev = spark.range(4000).selectExpr("cast('2024-01-01' as timestamp) + make_interval(0, 0, 0, 0, 0, 0, id * 400) ts", "id % 900 user_id", "if(id % 2 = 0, 'click', 'purchase') event_type")
    direct = windows.windowed_registers(ev, "user_id", *streams._sides(), F.window("ts", "7 days", "1 day"), 8)
    panes = windows.windowed_registers(ev, "user_id", *streams._sides(), F.window("ts", "1 day"), 8, over=("7 days", "1 day"))
    assert sorted(map(str, direct.collect())) == sorted(map(str, panes.collect()))
    ev.coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    plan = registry.queries()["window_sliding"](spark, str(tmp_path))._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("md5(") > max(plan.find("Expand"), plan.find("Generate explode(array(")) > 0  # hashed below, that is before, rows go to seven windows
    many = spark.range(600_000).selectExpr("id", "cast(rand(1) as string) x").coalesce(1)
    monkeypatch.setattr(windows, "shared_folder", lambda *a: str(tmp_path / "replay"))
    windows.replay(spark, [many])
    batch = pq.ParquetFile(next((tmp_path / "replay").glob("*.parquet")))
    assert batch.num_row_groups > 4


def test_counted_sizes_are_those_of_the_table(spark, tmp_path):
    spark.range(3000).where("id % 7 != 0").selectExpr("id o_orderkey").coalesce(1).write.parquet(f"{tmp_path}/orders.parquet")
    keys = {i for i in range(3000) if i % 7}
    for r in experiments.counted_grid(spark, str(tmp_path), (0.0, 0.25, 1.0), (64,)).collect():
        a, b = {k for k in keys if k < 100}, {k for k in keys if 100 - 100 * r.overlap <= k < 100 - 100 * r.overlap + 100 * r.size_ratio}
        assert (r.a, r.b, r.n) == (len(a), len(b), len(a & b))
    assert [tuple(r) for r in registry.queries()["case_probabilities"](spark, str(tmp_path)).orderBy("size_ratio", "overlap").collect()] == sorted(by_sql("case_probabilities", tmp_path, "orders"))


@pytest.mark.parametrize("name", [
    "case_probabilities",
    "fig1_bias",
    "fig1_bias_holds",
    "fig2_variance",
    "fig2_variance_holds",
    "fig2_variance_trends",
    "fig3_improvement",
    "fig3_improvement_holds",
    "fisher_grid",
    "hll_accuracy_simulated",
    "interval_coverage",
])
def test_experiments_read_a_given_table(spark, sf, name):
    assert "Relation [o_orderkey" in registry.queries()[name](spark, sf)._jdf.queryExecution().analyzed().toString()


def test_nested_scan_reads_the_orders(spark, sf):
    frame = registry.queries()["exact_naive_worked_example"](spark, sf)
    assert "Relation [o_orderkey" in frame._jdf.queryExecution().analyzed().toString()
    assert [tuple(r) for r in frame.collect()] == by_sql("exact_naive_worked_example", sf, "orders")


def test_exact_document_pairs_write_less_than_the_texts(spark, tmp_path, monkeypatch):
    """Repeated ids join their sets, and no array of a text without a partner, nor its shingles, is written."""
    import random

    r = random.Random(3)
    texts = [" ".join(f"w{r.randrange(10**6)}" for _ in range(400)) for _ in range(120)]
    rows = [(i, t) for i, t in enumerate(texts)] + [(200, texts[0]), (201, texts[1] + " one more"), (7, "some other text of the same document id")]
    spark.createDataFrame(rows, "doc_id long, text string").coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
    (tmp_path / "shared").mkdir()
    monkeypatch.setattr("tempfile.tempdir", str(tmp_path / "shared"))  # where a session without spark.checkpoint.dir writes
    got = sorted(tuple(x) for x in registry.queries()["doc_near_duplicates_exact"](spark, str(tmp_path)).collect())
    assert got == sorted(by_sql("doc_near_duplicates_exact", tmp_path, "documents")) and len(got) == 2
    assert sum(p.stat().st_size for p in (tmp_path / "shared").rglob("*.parquet")) < sum(len(t) for t in texts) / 4


def test_sketches_out_of_arrays_and_their_statistics(spark):
    sets = spark.range(60).selectExpr("id as g", "explode(sequence(id div 3 * 40, id div 3 * 40 + 20 + id)) as e")
    regs = registers.build_registers(sets, "e", ["g"], 64)
    arrays = sets.groupBy("g").agg(F.sort_array(F.collect_list(F.xxhash64(F.lit(0).cast("long"), F.col("e")))).alias("h"))
    packed = registers.sketch_arrays(arrays, "g", 64)
    assert sorted(map(tuple, packed.collect())) == sorted(map(tuple, registers.pack(regs, ["g"]).collect()))
    pairs = allpairs.packed_candidates(packed, "g", 2)
    want = {(r.x, r.y): r for r in pairstats.pair_stats_all(regs, "g", 64, pairs=pairs).collect()}
    got = allpairs.similar_pairs(packed, "g", 64, 2).collect()
    assert len(got) == len(want) > 50
    for r in got:
        assert r.asDict() == pytest.approx(want[r.x, r.y].asDict(), rel=1e-12)
