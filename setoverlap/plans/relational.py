"""What surrounds the methods: SQL and table functions, join strategies, outer joins, array sets, coordinated samples,
moments, and the laws of the analysis on grids."""

from __future__ import annotations

from pyspark.sql import functions as F

from setoverlap.functions import sqlfuncs, textsets
from setoverlap.functions.hashing import register_energy, register_unit
from setoverlap.operators import allpairs, cardinality, exact, mle, pairstats, registers, simulate, theory
from setoverlap.plans import sql, workloads as w
from setoverlap.plans.book import query
from setoverlap.sources.tables import load_table, register_views

_YEARS = "SELECT o_custkey AS e, bool_or(year(o_orderdate) = 1995) AS a, bool_or(year(o_orderdate) = 1996) AS b FROM orders GROUP BY 1"


@query(f"SELECT h AS hint, count(*) FILTER (a AND b) AS card_both FROM ({_YEARS}) q, unnest(['merge', 'shuffle_hash', 'broadcast']) x(h) GROUP BY 1")
def exact_join_strategies(spark, d):
    """The exact baseline under each join strategy."""
    o = load_table(spark, d, "orders")
    a, b = (o.where(F.year("o_orderdate") == y).select("o_custkey").distinct() for y in (1995, 1996))
    got = None
    for hint in ("merge", "shuffle_hash", "broadcast"):
        one = a.join(b.hint(hint), "o_custkey").agg(F.count("*").alias("card_both")).select(F.lit(hint).alias("hint"), "card_both")
        got = one if got is None else got.unionByName(one)
    return got


@query(f"SELECT count(*) FILTER (a AND NOT b) AS only_a, count(*) FILTER (a AND b) AS card_both, count(*) FILTER (b AND NOT a) AS only_b FROM ({_YEARS}) q")
def exact_full_outer(spark, d):
    o = load_table(spark, d, "orders")
    a, b = (o.where(F.year("o_orderdate") == y).select(F.col("o_custkey").alias("e"), F.lit(True).alias(s)).distinct() for y, s in ((1995, "a"), (1996, "b")))
    both = a.join(b, "e", "full_outer")
    return both.agg(F.count_if(F.col("b").isNull()).alias("only_a"), F.count_if(F.expr("a and b")).alias("card_both"), F.count_if(F.col("a").isNull()).alias("only_b"))


@query(r"SELECT conv_id, len(list_intersect(list_distinct(flatten(list(ws) FILTER (role = 'user'))), list_distinct(flatten(list(ws) FILTER (role = 'assistant'))))) AS card_both, len(list_distinct(flatten(list(ws)))) AS card_any FROM (SELECT conv_id, role, string_split_regex(lower(text), '\s+') AS ws FROM conversations WHERE role IN ('user', 'assistant')) q GROUP BY 1 HAVING count(*) FILTER (role = 'user') > 0 AND count(*) FILTER (role = 'assistant') > 0")
def conversation_array_overlap(spark, d):
    """Small sets as arrays of a row: what user and assistant of a conversation share."""
    said = load_table(spark, d, "conversations").where(F.col("role").isin("user", "assistant")).select("conv_id", "role", textsets.words(F.col("text")).alias("ws"))
    side = lambda r: F.array_distinct(F.flatten(F.collect_list(F.when(F.col("role") == r, F.col("ws"))))).alias(r)
    both = said.groupBy("conv_id").agg(side("user"), side("assistant"), F.count_if(F.col("role") == "user").alias("nu"), F.count_if(F.col("role") == "assistant").alias("na")).where("nu > 0 and na > 0")
    return both.select("conv_id", F.size(F.array_intersect("user", "assistant")).cast("long").alias("card_both"), F.size(F.array_union("user", "assistant")).cast("long").alias("card_any"))


_IN = "CAST('0x' || substr(md5('0:' || e), 1, 15) AS BIGINT) % 4 = 0"


@query(f"SELECT 4 * count(*) FILTER (a) AS card_a, 4 * count(*) FILTER (b) AS card_b, 4 * count(*) FILTER (a AND b) AS card_both FROM ({_YEARS}) q WHERE {_IN}")
def coordinated_sample(spark, d):
    """The same quarter of the elements on both sides, by their hash: a check that works at any size."""
    kept = exact.coordinated_sample(w.customers_by_year(spark, d), "e", 4, "md5")
    return exact.exact_sizes(kept, "e", F.col("in_a"), F.col("in_b")).select(*[(4 * F.col(c)).alias(c) for c in ("card_a", "card_b", "card_both")])


@query("SELECT r.r_name AS region, count(DISTINCT o.o_custkey) AS card FROM orders o JOIN customer c ON o.o_custkey = c.c_custkey JOIN nation n ON c.c_nationkey = n.n_nationkey JOIN region r ON n.n_regionkey = r.r_regionkey GROUP BY 1")
def sql_over_views(spark, d):
    """The tables as views of the session's catalog, asked in SQL."""
    register_views(spark, d, "setoverlap_", ["orders", "customer", "nation", "region"])
    return spark.sql("SELECT r_name AS region, count(DISTINCT o_custkey) AS card FROM setoverlap_orders JOIN setoverlap_customer ON o_custkey = c_custkey JOIN setoverlap_nation ON c_nationkey = n_nationkey JOIN setoverlap_region ON n_regionkey = r_regionkey GROUP BY 1")


_CRB = "((a + b - n) / 1000) / (1 / n + (b - n) / (a * a + (a - n) * (b - n)) + (a - n) / (b * b + (a - n) * (b - n)))"


@query(f"SELECT f AS size_ratio, o AS overlap, round({_CRB} / n / n * 1000, 6) AS bound, round(n / (a + b - n), 9) AS jaccard, round(1 - pow(1 - pow(n / (a + b - n), 2), 32), 9) AS recall FROM (SELECT f::DOUBLE AS f, (o / 10)::DOUBLE AS o, 1e6::DOUBLE AS a, 1e6::DOUBLE * f AS b, 1e5::DOUBLE * o AS n FROM unnest([1, 5, 10]) x(f), range(1, 10) y(o)) g")
def sql_functions(spark, d):
    sqlfuncs.register(spark)
    spark.range(1, 10).select(F.explode(F.array(F.lit(1.0), F.lit(5.0), F.lit(10.0))).alias("f"), (F.col("id") / 10).alias("o")).createOrReplaceTempView("setoverlap_grid")
    return spark.sql("SELECT f AS size_ratio, o AS overlap, round(intersection_bound(1e6D, f * 1e6D, o * 1e6D, 1000D) / (o * 1e6D) / (o * 1e6D) * 1000, 6) AS bound, round(jaccard_of(1e6D, f * 1e6D, o * 1e6D), 9) AS jaccard, round(band_recall(jaccard_of(1e6D, f * 1e6D, o * 1e6D), 2, 64), 9) AS recall FROM setoverlap_grid")


@query(r"SELECT item_id, count(DISTINCT e) AS n_shingles FROM (SELECT item_id, array_to_string(ws[i : i + 4], ' ') AS e FROM (SELECT item_id, regexp_extract_all(lower(text), '\S+') AS ws FROM benchmark) q, unnest(range(1, greatest(len(ws) - 3, 2))) u(i) WHERE len(ws) > 0) s GROUP BY 1")
def sql_table_function_shingles(spark, d):
    sqlfuncs.register(spark)
    register_views(spark, d, "setoverlap_", ["benchmark"])
    return spark.sql("SELECT item_id, count(*) AS n_shingles FROM setoverlap_benchmark, LATERAL shingles(text, 5) GROUP BY item_id")


@query(" UNION ALL ".join(f"SELECT {i}::INTEGER AS iter, round(card_both, 2) AS card_both FROM ({sql.newton(sql.stats(sql.pair_registers(w.S_YEAR, w.M), w.M), '', i)}) z" for i in range(5)))
def sql_table_function_newton(spark, d):
    sqlfuncs.register(spark)
    w.stats_of(w.customers_by_year(spark, d)).createOrReplaceTempView("setoverlap_stats")
    return spark.sql("SELECT iter, round(t.card_both, 2) AS card_both FROM setoverlap_stats s, LATERAL newton_trace(s.k_tie, s.k_b, s.k_a, s.sum_a, s.sum_b, s.sum_any, 4) t")


@query("SELECT event_type, true AS equal FROM events GROUP BY 1")
def sql_aggregate_pack(spark, d):
    """The grouped aggregate against the built-in packing."""
    sqlfuncs.register(spark)
    regs = registers.build_registers(load_table(spark, d, "events"), "user_id", ["event_type"], 16)
    regs.createOrReplaceTempView("setoverlap_registers")
    got = spark.sql("SELECT event_type, register_pack(k, v) AS packed FROM setoverlap_registers GROUP BY event_type")
    return got.join(registers.pack(regs, ["event_type"]), "event_type").select("event_type", (F.col("packed") == F.col("regs")).alias("equal"))


_DAYS = sql.newton(sql.stats(sql.pair_registers(w.S_FLOWS, w.M, "day"), w.M, "day"), "day")


@query(f"SELECT round(avg(card_both), 2) AS mean, round(var_pop(card_both), 2) AS variance, round(stddev_pop(card_both), 2) AS deviation, round(covar_pop(card_a, card_b), 1) AS covariance, round(corr(card_a, card_both), 4) AS correlation FROM ({_DAYS}) q")
def flow_moments(spark, d):
    e = mle.mle_intersection(w.stats_of(w.shared_flows(spark, d), ["day"]))
    return e.agg(F.round(F.avg("card_both"), 2).alias("mean"), F.round(F.var_pop("card_both"), 2).alias("variance"), F.round(F.stddev_pop("card_both"), 2).alias("deviation"), F.round(F.covar_pop("card_a", "card_b"), 1).alias("covariance"), F.round(F.corr("card_a", "card_both"), 4).alias("correlation"))


@query("SELECT s AS o_orderstatus, true AS approx_close, true AS hll_close, true AS theta_close FROM (SELECT DISTINCT o_orderstatus AS s FROM orders) q")
def native_cardinalities(spark, d):
    """Spark's own three estimates within 6 % of the exact count."""
    o = load_table(spark, d, "orders")
    got = cardinality.native_cardinality(o, "o_custkey", ["o_orderstatus"]).join(cardinality.exact_cardinality(o, "o_custkey", ["o_orderstatus"]), "o_orderstatus")
    near = lambda c: (F.abs(F.col(c) - F.col("card")) <= 0.06 * F.col("card") + 1)
    return got.select("o_orderstatus", near("card_approx").alias("approx_close"), near("card_hll_native").alias("hll_close"), near("card_theta").alias("theta_close"))


@query("SELECT true AS close")
def native_theta(spark, d):
    """Spark's theta-sketch intersection within 10 % of the exact overlap."""
    y, o = F.year("o_orderdate"), load_table(spark, d, "orders")
    both = cardinality.native_theta_intersection(o, "o_custkey", y == 1995, y == 1996).crossJoin(w.exact_of(w.customers_by_year(spark, d)).select(F.col("card_both").alias("n")))  # one row each
    return both.select((F.abs(F.col("card_both") - F.col("n")) <= 0.1 * F.col("n") + 1).alias("close"))


@query("WITH s AS (SELECT DISTINCT l_suppkey AS g, l_partkey AS e FROM lineitem) SELECT a.g AS x, b.g AS y, count(*) AS card_both FROM s a JOIN s b ON a.e = b.e AND a.g < b.g GROUP BY 1, 2 ORDER BY card_both DESC, x, y LIMIT 20")
def supplier_pairs_top20_exact(spark, d):
    """The pairs that share most parts by exact counts (16 registers in ml_supplier_pairs_top20 draw theirs from noise)."""
    pairs = allpairs.exact_pair_overlaps(load_table(spark, d, "lineitem"), "l_suppkey", "l_partkey")
    return pairs.select("x", "y", "card_both").orderBy(F.desc("card_both"), "x", "y").limit(20)


# --- likelihood register by register, and laws on grids ---------------------------------------------------------------------------

_AT = f"SELECT *, share * least(a, b) AS n FROM (SELECT *, m / sum_a AS a, m / sum_b AS b, unnest([0.3, 0.5, 0.6, 0.7, 0.8, 0.9])::DOUBLE AS share FROM ({sql.stats(sql.pair_registers(w.S_YEAR, w.M), w.M)}) s) q"
_LL = "k_tie * ln(n) + k_b * ln((b - n) * a) + k_a * ln((a - n) * b) - a * sum_a - b * sum_b + n * sum_any"


@query(f"WITH z AS (SELECT share, {_LL} AS ll FROM ({_AT}) x) SELECT share, round(ll - (SELECT ll FROM z WHERE share = 0.3), 4) AS gain FROM z")
def likelihood_by_registers(spark, d):
    """Sum of the log densities of all registers, above its value at the first point: the closed form's differences."""
    regs = registers.pair_registers(w.customers_by_year(spark, d), "e", F.col("in_a"), F.col("in_b"), m=w.M, family="md5")
    s = pairstats.pair_stats(regs, m=w.M, family="md5").select((F.col("m") / F.col("sum_a")).alias("a"), (F.col("m") / F.col("sum_b")).alias("b"))
    at = s.withColumn("share", F.explode(F.array(*[F.lit(x) for x in (0.3, 0.5, 0.6, 0.7, 0.8, 0.9)]))).withColumn("n", F.col("share") * F.least("a", "b"))
    x = lambda v: 1 - register_unit(F.col(v), "md5")
    ll = regs.crossJoin(F.broadcast(at)).groupBy("share").agg(F.sum(F.ln(mle.case_density(x("va"), x("vb"), F.col("a"), F.col("b"), F.col("n")))).alias("ll"))  # six rows
    return ll.crossJoin(F.broadcast(ll.where("share = 0.3").select(F.col("ll").alias("first")))).select("share", F.round(F.col("ll") - F.col("first"), 4).alias("gain"))  # one row


@query("SELECT c::BIGINT AS c, x / 10.0::DOUBLE AS x, round(c * pow(x / 10.0::DOUBLE, c - 1), 9) AS pdf, round(pow(x / 10.0::DOUBLE, c), 9) AS cdf, true AS beta_agrees FROM unnest([1, 2, 5, 20]) t(c), range(1, 10) r(x)")
def max_hash_law(spark, d):
    """Density and distribution of a set's largest hash, and the general beta law beside them."""
    c = F.col("c").cast("double")
    beta = theory.beta_pdf_column(F.col("x"), c, F.lit(1.0))
    g = spark.range(1, 10).select((F.col("id") / 10).alias("x"), F.explode(F.array(*[F.lit(k).cast("long") for k in (1, 2, 5, 20)])).alias("c"))
    pdf = theory.max_hash_pdf(F.col("x"), c)
    return g.select("c", "x", F.round(pdf, 9).alias("pdf"), F.round(theory.max_hash_cdf(F.col("x"), c), 9).alias("cdf"), (F.abs(beta - pdf) <= 1e-9 * pdf).alias("beta_agrees"))


_G = "SELECT f::DOUBLE AS size_ratio, o / 10.0::DOUBLE AS overlap, 1e6::DOUBLE AS a, 1e6::DOUBLE * f AS b, 1e5::DOUBLE * o AS n, 1e6::DOUBLE + 1e6 * f - 1e5 * o AS u FROM unnest([1, 5, 10]) x(f), range(1, 11) y(o)"


@query(f"SELECT size_ratio, overlap, round(n / u * (1 - n / u), 9) AS var_jaccard, round((n / u * n / u * u * u + u * u * n / u * (1 - n / u)) / n / n, 6) AS var_product, round(u * u / 1e12, 6) AS hll_lemma, round(1.04 * 1.04 * u * u / 1e12, 6) AS hll_published FROM ({_G}) g")
def law_pieces(spark, d):
    """m times: variance of the tie share; of its product with an independent union size, over n^2 (the second scheme's
    law); of a log-log size, both variants, over |A|^2."""
    g = simulate.experiment_grid(spark, overlaps=[i / 10 for i in range(1, 11)], ms=(1000,))
    a, m = F.col("a"), F.col("m").cast("double")
    b, n = a * F.col("size_ratio"), a * F.col("overlap")
    u = a + b - n
    j = n / u
    product = theory.product_variance(j, theory.jaccard_variance(j, m), u, cardinality.hll_variance(u, m))
    return g.select("size_ratio", "overlap", F.round(theory.jaccard_variance(j, m) * m, 9).alias("var_jaccard"), F.round(product * m / n / n, 6).alias("var_product"), F.round(cardinality.hll_variance(u, m) * m / a / a, 6).alias("hll_lemma"), F.round(cardinality.hll_variance(u, m, "published") * m / a / a, 6).alias("hll_published"))


@query("SELECT event_type, true AS equal FROM events GROUP BY 1")
def energies_in_sql(spark, d):
    """The SQL function of a register's energy equals the column function."""
    sqlfuncs.register(spark)
    regs = registers.build_registers(load_table(spark, d, "events"), "user_id", ["event_type"], 16)
    return regs.groupBy("event_type").agg(F.bool_and(F.abs(F.expr("register_energy(v)") - register_energy(F.col("v"))) <= 1e-15).alias("equal"))
