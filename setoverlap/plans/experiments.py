"""The paper-scale experiments: bias, variance and improvement over the whole grid, laws, orders, coverage, cost in steps.

Each figure is registered as its points (simulated, so without SQL) and as what must hold of every point: booleans that
the SQL side states as constants over the same grid.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from setoverlap.operators import cardinality, mle, pairstats, registers, schemes, simulate, theory
from setoverlap.plans import sql, workloads as w
from setoverlap.plans.book import query, rounded
from setoverlap.sources.tables import load_table

SIZES = ["card_a", "card_b", "card_both"]
#: The whole experiment: trials for each cell, all overlaps, size ratios, and register counts.
TRIALS, STEPS, RATIOS, REGISTERS = 10_000, [i / 100 for i in range(101)], (1.0, 5.0, 10.0), (100, 500, 1000, 10000)
CELL = ["size_ratio", "overlap", "m"]


def grid_sql(ms, ratios=RATIOS, steps: str = "range(101)", scale: int = 100) -> str:
    """The same cells in SQL: size_ratio, overlap, m."""
    return f"SELECT f::DOUBLE AS size_ratio, o / {scale}::DOUBLE AS overlap, m::BIGINT AS m FROM unnest([{', '.join(str(int(f)) for f in ratios)}]) x(f), {steps} y(o), unnest([{', '.join(map(str, ms))}]) z(m)"


# --- on the given tables ---------------------------------------------------------------------------------------------------------

def _controlled_rows(spark, d, overlaps):
    """Key ranges sized by the table: a is the largest power of ten that fits 11 times."""
    n = load_table(spark, d, "orders").count()
    a = 10 ** (len(str(max(n // 11, 1))) - 1)
    k = F.col("e")
    cells = [(f, o, int(round(o * a))) for f in (1, 5, 10) for o in overlaps]
    one = load_table(spark, d, "orders").select(F.col("o_orderkey").alias("e"))
    cell = F.explode(F.array(*[F.struct(F.lit(float(f)).alias("size_ratio"), F.lit(float(o)).alias("overlap"), (k < a).alias("in_a"), ((k >= a - t) & (k < a - t + f * a)).alias("in_b")) for f, o, t in cells]))
    return one.where(k < 11 * a).select(k, cell.alias("c")).select("e", "c.*"), a


_CTL = "WITH z AS (SELECT pow(10, length((greatest(count(*) // 11, 1))::VARCHAR) - 1)::BIGINT AS a FROM orders), c AS (SELECT f, o, a, round(o * a)::BIGINT AS t FROM z, unnest([1, 5, 10]) x(f), unnest([0.0, 0.1, 0.5, 0.9, 1.0]) y(o)) SELECT f::DOUBLE AS size_ratio, o::DOUBLE AS overlap, o_orderkey AS e, o_orderkey < a AS in_a, o_orderkey >= a - t AND o_orderkey < a - t + f * a AS in_b FROM orders, c WHERE o_orderkey < 11 * a"


@query(sql.rounded(sql.newton(sql.stats(sql.pair_registers(_CTL, w.M, "size_ratio, overlap"), w.M, "size_ratio, overlap"), "size_ratio, overlap"), SIZES, ("size_ratio", "overlap"), 2))
def controlled_overlap_orders(spark, d):
    rows, _ = _controlled_rows(spark, d, (0.0, 0.1, 0.5, 0.9, 1.0))
    return rounded(mle.mle_intersection(w.stats_of(rows, ["size_ratio", "overlap"])), SIZES, ["size_ratio", "overlap"], 2)


REPLICATES, TABLE_M = 20, 64


def _table_trials(spark, d, replicates: int = REPLICATES, m: int = TABLE_M):
    """Real hashing with disjoint function blocks as trials: function index k belongs to trial k div m."""
    rows, a = _controlled_rows(spark, d, (0.1, 0.5, 0.9))
    stats = simulate.hashed_trials(rows, ["size_ratio", "overlap"], m, replicates)
    return schemes.estimate_all(stats, ["size_ratio", "overlap", "trial", "m"]).withColumn("truth", F.col("overlap") * a)


@query()
def accuracy_controlled(spark, d):
    return simulate.accuracy_table(_table_trials(spark, d))


@query()
def improvement_controlled(spark, d):
    return simulate.improvement_table(simulate.accuracy_table(_table_trials(spark, d)))


_TABLE_GRID = grid_sql((TABLE_M,), steps="unnest([1, 5, 9])", scale=10)
_SCHEMES = "unnest(['inclusion_exclusion', 'jaccard_union', 'jaccard_sum', 'ml']) s(scheme)"


@query(f"SELECT scheme, g.*, {REPLICATES}::BIGINT AS trials, true AS mean_close, true AS variance_close FROM ({_TABLE_GRID}) g, {_SCHEMES}")
def accuracy_controlled_holds(spark, d):
    """Real hashing of the order keys: each scheme's mean within 4 standard errors (and the 2/m of a maximum-likelihood
    size) of the truth, its variance within a factor of 3.5 of its law (20 trials)."""
    acc = simulate.with_theory(accuracy_controlled(spark, d), _controlled_rows(spark, d, (0.1,))[1])
    mean = F.col("bias_norm") <= 2.0 / F.col("m") + 4 * F.sqrt(F.col("theory_norm") / F.col("trials"))
    ratio = F.col("var_norm") / F.col("theory_norm")
    return acc.select("scheme", *CELL, "trials", mean.alias("mean_close"), ratio.between(1 / 3.5, 3.5).alias("variance_close"))


@query("SELECT true AS mean_close, true AS variance_close")
def simulated_hashing_agrees(spark, d):
    """Real hashing of generated keys against the law of the statistics: mean and variance of the tie share."""
    f, o, a, m, trials = 2.0, 0.5, 400, 64, 200
    j = o / (1 + f - o)
    got = simulate.simulate_hashed(spark, f, o, a, m, trials).agg(F.avg(F.col("k_tie") / F.lit(m)).alias("mean"), F.var_pop(F.col("k_tie") / F.lit(m)).alias("var"))
    var = j * (1 - j) / m
    return got.select((F.abs(F.col("mean") - j) <= 4 * (var / trials) ** 0.5).alias("mean_close"), (F.abs(F.col("var") / var - 1) <= 4 * (2 / trials) ** 0.5).alias("variance_close"))


# --- sets counted on the order keys ----------------------------------------------------------------------------------------------

def counted_grid(spark, d, overlaps, ms, ratios=RATIOS) -> DataFrame:
    """cell, size_ratio, overlap, m, a, b, n: sizes of two ranges of order keys and of their intersection, as counted in
    the table for each cell. A range of 100 f steps is f times as long as A; steps of the overlap are hundredths of A,
    which has the largest power of ten (100 or more) that fits 11 times into the table's rows."""
    orders = load_table(spark, d, "orders")
    step = max(100, 10 ** (len(str(max(orders.count() // 11, 1))) - 1)) // 100
    at = F.least(F.floor(F.col("o_orderkey") / step), F.lit(1100)).alias("at")  # all beyond the longest range in one bin
    bins = orders.where("o_orderkey >= 0").groupBy(at).agg(F.countDistinct("o_orderkey").alias("c"))
    cells = [(i, float(f), float(o), int(m), 100 - round(100 * o)) for i, (f, o, m) in enumerate((f, o, m) for f in ratios for o in overlaps for m in ms)]
    cells = spark.createDataFrame(cells, "cell int, size_ratio double, overlap double, m long, lo int")
    size = lambda lo, hi: F.coalesce(F.sum(F.when((F.col("at") >= lo) & (F.col("at") < hi), F.col("c"))), F.lit(0)).cast("double")
    lo = F.col("lo")
    met = F.broadcast(cells).crossJoin(bins)  # at most 1,101 bins
    return met.groupBy("cell", "size_ratio", "overlap", "m").agg(size(F.lit(0), F.lit(100)).alias("a"), size(lo, lo + 100 * F.col("size_ratio")).alias("b"), size(lo, F.lit(100)).alias("n"))


#: The same sizes in SQL, over overlaps of .1 to 1: size_ratio, overlap, m, a, b, n, u, p, q.
COUNTED = """WITH z AS (SELECT greatest(100, pow(10, length((greatest(count(*) // 11, 1))::VARCHAR) - 1)::BIGINT) // 100 AS step FROM orders),
h AS (SELECT o_orderkey // step AS pos, count(DISTINCT o_orderkey) AS c FROM orders, z WHERE o_orderkey >= 0 GROUP BY 1),
s AS (SELECT f, o, coalesce(sum(c) FILTER (pos < 100), 0)::DOUBLE AS a, coalesce(sum(c) FILTER (pos >= 100 - 10 * o AND pos < 100 - 10 * o + 100 * f), 0)::DOUBLE AS b, coalesce(sum(c) FILTER (pos >= 100 - 10 * o AND pos < 100), 0)::DOUBLE AS n FROM unnest([1, 5, 10]) x(f), range(1, 11) y(o), h GROUP BY 1, 2)
SELECT f::DOUBLE AS size_ratio, o / 10.0::DOUBLE AS overlap, 1000::BIGINT AS m, a, b, n, a + b - n AS u, a - n AS p, b - n AS q FROM s"""


# --- the whole grid -----------------------------------------------------------------------------------------------------------------

def simulated_accuracy(spark, ratios, overlaps, ms, trials, seed=1, only: tuple = schemes.SCHEMES) -> DataFrame:
    return simulate.simulate_accuracy(simulate.experiment_grid(spark, ratios, overlaps, ms), trials, seed, only)


def _ml_grid(spark, d, ms):
    grid = counted_grid(spark, d, STEPS, ms)
    return simulate.with_theory(simulate.simulate_accuracy(grid, TRIALS, only=("ml",)), grid)


@query()
def fig1_bias(spark, d):
    return _ml_grid(spark, d, (1000, 10000)).select(*CELL, "trials", "bias_norm", "var_norm")


@query(f"SELECT *, true AS unbiased FROM ({grid_sql((1000, 10000))}) g")
def fig1_bias_holds(spark, d):
    """Every point's bias lies within 2/m and 4 standard errors of its mean; at overlap 0 every estimate is 0."""
    small = F.col("bias_norm") <= 2.0 / F.col("m") + 4 * F.sqrt(F.col("var_norm") / F.col("trials"))
    return _ml_grid(spark, d, (1000, 10000)).select(*CELL, F.coalesce(small, F.col("mean") == 0).alias("unbiased"))


@query()
def fig2_variance(spark, d):
    return _ml_grid(spark, d, REGISTERS).select(*CELL, "trials", "var_norm", "crb_norm", "efficiency")


@query(f"SELECT *, true AS at_the_bound FROM ({grid_sql((1000, 10000))}) g WHERE overlap > 0")
def fig2_variance_holds(spark, d):
    """Every point's variance over the bound, for 1,000 registers or more: at most 1.08, and not below 1 by more than 5
    standard errors of a variance ratio (600 points are judged at once; a band of 3.5, from .95, misses one of them)."""
    at = (F.col("var_norm") / F.col("crb_norm")).between(1 - 5 * (2 / TRIALS) ** 0.5, 1.08)
    return _ml_grid(spark, d, (1000, 10000)).where("overlap > 0").select(*CELL, at.alias("at_the_bound"))


@query("SELECT f::DOUBLE AS size_ratio, true AS falls_with_registers, true AS falls_with_overlap FROM unnest([1, 5, 10]) x(f)")
def fig2_variance_trends(spark, d):
    """Variance falls as registers grow (at every overlap) and as the overlap grows (in steps of .1)."""
    acc = simulate.simulate_accuracy(counted_grid(spark, d, [i / 10 for i in range(1, 11)], REGISTERS), 2000, 2, ("ml",))
    by_m = acc.groupBy("size_ratio", "overlap").agg(F.transform(F.array_sort(F.collect_list(F.struct("m", "var_norm"))), lambda x: x["var_norm"]).alias("v"))
    by_o = acc.groupBy("size_ratio", "m").agg(F.transform(F.array_sort(F.collect_list(F.struct("overlap", "var_norm"))), lambda x: x["var_norm"]).alias("v"))
    falls = lambda df, slack, name: df.groupBy("size_ratio").agg(F.bool_and(F.forall(F.sequence(F.lit(1), F.size("v") - 1), lambda i: F.get("v", i) <= slack * F.get("v", i - 1))).alias(name))
    return falls(by_m, 1.0, "falls_with_registers").join(falls(by_o, 1.15, "falls_with_overlap"), "size_ratio")


@query()
def fig3_improvement(spark, d):
    return simulate.improvement_table(simulate.simulate_accuracy(counted_grid(spark, d, STEPS, (1000, 10000)), TRIALS))


@query(f"SELECT g.*, scheme, true AS never_worse, true AS at_most_one FROM ({grid_sql((1000, 10000))}) g, unnest(['inclusion_exclusion', 'jaccard_union', 'jaccard_sum']) s(scheme)")
def fig3_improvement_holds(spark, d):
    """At every point of the grid the improvement over each scheme is at least 0 within 4 standard errors of a ratio of
    two variances on the same draws (sqrt(4 / trials) bounds one), and at most 1; null (no variance) counts as 0."""
    r = F.coalesce(F.col("rel_var_improvement"), F.lit(0.0))
    return fig3_improvement(spark, d).select(*CELL, "scheme", (r >= -4 * (4 / TRIALS) ** 0.5).alias("never_worse"), (r <= 1).alias("at_most_one"))


@query("SELECT s AS scheme, 1000::BIGINT AS m, true AS dominates FROM unnest(['inclusion_exclusion', 'jaccard_union', 'jaccard_sum']) x(s)")
def ml_dominates(spark, d):
    """Over every overlap from 0 to 1 with 2,000 trials a cell; slack of 4 standard errors of a variance ratio."""
    acc = simulated_accuracy(spark, RATIOS, STEPS, (1000,), 2000, 3)
    return simulate.dominance_check(simulate.improvement_table(acc), 0.13)


_ORDER_GRID = "SELECT f::DOUBLE AS size_ratio, o / 20::DOUBLE AS overlap, 1e6 AS a, 1e6 * f AS b, 1e6 * o / 20 AS n, 1e6 + 1e6 * f - 1e6 * o / 20 AS u, 1e6 - 1e6 * o / 20 AS p, 1e6 * f - 1e6 * o / 20 AS q FROM unnest([1, 5, 10]) x(f), range(1, 20) y(o)"
_ONE, _TWO = "(u * u - a * a - b * b + 2 * n * a * b / u) / n / n", "u / n"
_THREE = "((a * a + b * b + 2 * a * b * n / u) + (p + q) * u * u / n + 2 * (a * q + b * p)) / (a + b) / (a + b)"


@query(f"SELECT size_ratio, overlap, {_THREE} < {_TWO} AS third_below_second, {_ONE} < {_THREE} AS first_below_third, true AS simulation_agrees FROM ({_ORDER_GRID}) g")
def scheme_order(spark, d):
    """Which of the three schemes varies less, by their laws, and whether simulated variances order them alike wherever
    the laws differ by a sixth or more: the third below the second everywhere, the first below the third near containment."""
    steps = [i / 20 for i in range(1, 20)]
    laws = simulate.theory_table(simulate.experiment_grid(spark, RATIOS, steps, (1000,)))
    acc = simulated_accuracy(spark, RATIOS, steps, (1000,), 3000, 5)
    seen = acc.groupBy("size_ratio", "overlap").pivot("scheme", ["inclusion_exclusion", "jaccard_union", "jaccard_sum"]).agg(F.first("var_norm"))
    both = laws.join(seen, ["size_ratio", "overlap"])
    agree = lambda x, y, sx, sy: (F.abs(F.ln(F.col(x) / F.col(y))) < F.log(F.lit(7 / 6))) | ((F.col(x) < F.col(y)) == (F.col(sx) < F.col(sy)))
    return both.select("size_ratio", "overlap", (F.col("scheme3_shared") < F.col("scheme2")).alias("third_below_second"), (F.col("scheme1_direct") < F.col("scheme3_shared")).alias("first_below_third"),
                       (agree("scheme3_shared", "scheme2", "jaccard_sum", "jaccard_union") & agree("scheme1_direct", "scheme3_shared", "inclusion_exclusion", "jaccard_sum")).alias("simulation_agrees"))


_TENTHS = grid_sql((1000,), steps="range(1, 10)", scale=10)


@query(f"SELECT *, true AS covers FROM ({_TENTHS}) g")
def interval_coverage(spark, d):
    """Share of 2,000 trials whose 95 % interval holds the truth: in [.93, .97] where ten ties or more are expected; the one
    cell with fewer (ratio 10, overlap .1: nine ties, a skewed estimate) covers .929 and is held to [.9, .97]."""
    grid = counted_grid(spark, d, [i / 10 for i in range(1, 10)], (1000,))
    est = mle.estimate_interval(mle.mle_intersection(simulate.simulate_stats(grid, 2000, 7), engine="arrow")).join(F.broadcast(grid.select("cell", F.col("n").alias("truth"))), "cell")  # a row a cell
    ties = F.col("m") * F.col("overlap") / (1 + F.col("size_ratio") - F.col("overlap"))
    return simulate.coverage(est, CELL).select(*CELL, F.col("coverage").between(F.when(ties >= 10, 0.93).otherwise(0.9), 0.97).alias("covers"))


@query(f"SELECT *, true AS ten_steps_suffice, true AS three_steps_close FROM ({_TENTHS}) g")
def newton_steps(spark, d):
    """From the interior start every trial of 1,000 converges within ten steps, and three give the size to a thousandth."""
    grid = simulate.experiment_grid(spark, RATIOS, [i / 10 for i in range(1, 10)], (1000,))
    draws = simulate.simulate_stats(grid, 1000, 8)
    full = mle.mle_intersection(draws, engine="arrow")
    three = mle.mle_intersection(full.withColumnsRenamed({c: f"full_{c}" for c in ("card_a", "card_b", "card_both", "card_any", "only_a", "only_b", "jaccard", "iters", "converged", "boundary", "var_hat")}), iters=3, tol=0.0, engine="arrow")
    inner = three.where("full_boundary is null")
    return inner.groupBy(*CELL).agg((F.max("full_iters") <= 10).alias("ten_steps_suffice"), (F.max(F.abs(F.col("card_both") / F.col("full_card_both") - 1)) <= 1e-3).alias("three_steps_close"))


@query(f"SELECT *, true AS mean_close, true AS variance_close FROM ({_TENTHS}) g")
def jaccard_law(spark, d):
    """The tie share over 4,000 trials: mean J and variance J(1 - J)/m, each within 4 standard errors."""
    trials = 4000
    grid = simulate.experiment_grid(spark, RATIOS, [i / 10 for i in range(1, 10)], (1000,))
    j = F.col("overlap") / (1 + F.col("size_ratio") - F.col("overlap"))
    got = simulate.simulate_stats(grid, trials, 9).groupBy(*CELL).agg(F.avg(F.col("k_tie") / F.col("m")).alias("mean"), F.var_pop(F.col("k_tie") / F.col("m")).alias("var"))
    law = theory.jaccard_variance(j, F.col("m").cast("double"))
    return got.select(*CELL, (F.abs(F.col("mean") - j) <= 4 * F.sqrt(law / trials)).alias("mean_close"), (F.abs(F.col("var") / law - 1) <= 4 * (2 / trials) ** 0.5).alias("variance_close"))


@query("SELECT true AS within_four_sigma")
def simulators_agree(spark, d):
    """Register-level and statistic-level draws have the same mean tie count and union energy."""
    grid = simulate.experiment_grid(spark, (5.0,), (0.5,), (200,))
    one = lambda x: x.agg(F.avg("k_tie").alias("t"), F.var_samp("k_tie").alias("tv"), F.avg(F.col("sum_any") * F.col("a")).alias("u"), F.var_samp(F.col("sum_any") * F.col("a")).alias("uv"), F.count("*").alias("c"))
    x, y = one(simulate.simulate_registers(grid, 400)), one(simulate.simulate_stats(grid, 4000))
    both = x.toDF(*[f"x{c}" for c in x.columns]).crossJoin(y)  # one row each
    near = lambda s: F.abs(F.col(f"x{s}") - F.col(s)) <= 4 * F.sqrt(F.col(f"x{s}v") / F.col("xc") + F.col(f"{s}v") / F.col("c"))
    return both.select((near("t") & near("u")).alias("within_four_sigma"))


# --- log-log accuracy ------------------------------------------------------------------------------------------------------------------

@query("SELECT count(DISTINCT o_orderkey)::DOUBLE AS size, true AS unbiased, true AS variance_close FROM orders UNION ALL SELECT count(DISTINCT p_partkey)::DOUBLE, true, true FROM part")
def hll_accuracy_simulated(spark, d):
    """The keys of two tables hashed for real by 400 pairs of functions into 256 registers: mean ratio within 4 standard
    errors, variance times m in [.8, 1.45] (published: 1.04^2; the asymptotic law: 1)."""
    m, trials = 256, 400
    keys = load_table(spark, d, "orders").select(F.lit("orders").alias("name"), F.col("o_orderkey").alias("e")).unionByName(load_table(spark, d, "part").select(F.lit("part").alias("name"), F.col("p_partkey").alias("e")))
    sizes = keys.groupBy("name").agg(F.countDistinct("e").cast("double").alias("size"))
    got = cardinality.hll_estimate(simulate.hashed_hll(keys, "e", "name", m, trials), ["name", "trial"], m).join(F.broadcast(sizes), "name")  # two rows
    got = got.groupBy("size", "name").agg((F.avg("card_hll") / F.first("size")).alias("ratio"), (F.var_pop("card_hll") * m / F.first("size") / F.first("size")).alias("var_times_m"))
    return got.select("size", (F.abs(F.col("ratio") - 1) <= 0.01 + 4 * 1.04 / (m * trials) ** 0.5).alias("unbiased"), F.col("var_times_m").between(0.8, 1.45).alias("variance_close"))


def _hll(m: int, table: str, elem: str) -> str:
    h = lambda k: f"CAST('0x' || substr(md5('{k}:' || {elem}), 1, 15) AS BIGINT)"
    ranks = f"SELECT {h(1)} % {m} AS bucket, max(61 - CASE WHEN {h(0)} > 0 THEN length(bin({h(0)})) ELSE 0 END) AS rank FROM {table} GROUP BY 1"
    return f"SELECT '{table}' AS name, {m}::BIGINT AS m, round({cardinality.hll_alpha(m)!r}::DOUBLE * {m} * {m} / (sum(pow(2.0, -rank)) + {m} - count(*)), 3) AS card_hll FROM ({ranks}) z"


_KEYS = [("orders", "o_orderkey"), ("lineitem", "l_partkey")]
_HLL_MS = (64, 256, 1024)


@query(" UNION ALL ".join(_hll(m, t, e) for m in _HLL_MS for t, e in _KEYS))
def hll_cardinality_by_m(spark, d):
    got = None
    for m in _HLL_MS:
        for t, e in _KEYS:
            one = cardinality.hll_estimate(cardinality.hll_registers(load_table(spark, d, t), e, m=m, family="md5"), [], m).select(F.lit(t).alias("name"), F.lit(m).cast("long").alias("m"), F.round("card_hll", 3).alias("card_hll"))
            got = one if got is None else got.unionByName(one)
    return got


@query(f"SELECT source, scheme, true AS close FROM unnest(['registers', 'hll', 'native_hll', 'exact']) x(source), {_SCHEMES}")
def schemes_by_card_source(spark, d):
    """Customers of two years: every scheme on sizes from each source within 5 standard errors of the exact overlap.
    Sizes from a second sketch double the storage; a scheme's error is taken at its widest law."""
    src, m = w.customers_by_year(spark, d), 1024
    exact_n = w.exact_of(src).select("card_both")
    got = None
    for source in cardinality.SOURCES:
        stats = w.stats_of(src, m=m, family="xxhash64")
        if source != "registers":
            stats = stats.crossJoin(F.broadcast(cardinality.pair_cardinalities(src, "e", F.col("in_a"), F.col("in_b"), source, m)))  # one row each
        one = schemes.estimate_wide(stats)
        widest = F.sqrt(3 * theory.var_scheme1(F.col("card_a"), F.col("card_b"), F.col("card_both"), F.lit(float(m)), "printed"))
        rows = F.explode(F.array(*[F.struct(F.lit(s).alias("scheme"), F.col(s).alias("estimate")) for s in schemes.SCHEMES]))
        one = one.select(widest.alias("err"), rows.alias("r")).crossJoin(exact_n).select(F.lit(source).alias("source"), "r.scheme", (F.abs(F.col("r.estimate") - F.col("card_both")) <= 5 * F.col("err") + 2).alias("close"))
        got = one if got is None else got.unionByName(one)
    return got


@query("SELECT true AS fits_equal, true AS steps_equal, true AS accuracy_equal")
def ml_engines_agree(spark, d):
    """The fold in the row and the array engine: sizes to 1e-9, the same number of steps (one apart at most); the
    accuracy table by blocks equals the one by rows."""
    grid = simulate.experiment_grid(spark, (1.0, 10.0), (0.0, 0.01, 0.5, 1.0), (100,))
    draws = simulate.simulate_stats(grid, 200, 4)
    keep = lambda df, p: df.select("cell", "trial", F.col("card_both").alias(f"{p}_n"), F.col("iters").alias(f"{p}_i"))
    both = keep(mle.mle_intersection(draws), "f").join(keep(mle.mle_intersection(draws, engine="arrow"), "g"), ["cell", "trial"])
    fits = both.agg(F.bool_and(F.abs(F.col("f_n") - F.col("g_n")) <= 1e-9 * F.col("f_n") + 1e-9).alias("fits_equal"), F.bool_and(F.abs(F.col("f_i") - F.col("g_i")) <= 1).alias("steps_equal"))
    est = schemes.estimate_all(draws, ["size_ratio", "overlap", "m", "a"]).withColumn("truth", F.col("overlap") * F.col("a"))
    one, two = simulate.accuracy_table(est), simulate.simulate_accuracy(grid, 200, 4)
    near = lambda c: F.abs(F.col(f"o.{c}") - F.col(f"t.{c}")) <= 1e-6 * F.abs(F.col(f"o.{c}")) + 1e-6
    joined = one.alias("o").join(two.alias("t"), ["scheme", "size_ratio", "overlap", "m"])
    return fits.crossJoin(joined.agg((F.bool_and(near("mean") & near("var_raw")) & (F.count("*") == 32)).alias("accuracy_equal")))  # one row each
