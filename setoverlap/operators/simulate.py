"""The experiment engine: a grid of overlaps and size ratios, trials drawn at three levels, accuracy measures."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from setoverlap.functions.hashing import element_hash, mixed_long, slot_seeds
from setoverlap.operators import theory
from setoverlap.operators.mle import fit_arrays
from setoverlap.operators.pairstats import pair_stats
from setoverlap.operators.registers import pair_registers

BLOCK = 500
STATS = "cell int, trial long, size_ratio double, overlap double, a double, m long, k_tie long, k_b long, k_a long, k_b_seen long, k_a_seen long, sum_a double, sum_b double, sum_any double, scale double"


def experiment_grid(spark: SparkSession, ratios=(1.0, 5.0, 10.0), overlaps=None, ms=(1000,), a: float = 1e6) -> DataFrame:
    overlaps = [i / 100 for i in range(101)] if overlaps is None else list(overlaps)
    if not all(0 <= o <= 1 for o in overlaps) or not all(f >= 1 for f in ratios):
        raise ValueError("overlap lies in 0..1 and the size ratio is at least 1")
    cells = [(f, o, m) for f in ratios for o in overlaps for m in ms]
    return spark.createDataFrame([(i, float(f), float(o), int(m), float(a)) for i, (f, o, m) in enumerate(cells)], "cell int, size_ratio double, overlap double, m long, a double")


def _sizes(r: dict) -> tuple[float, float, float]:
    """|A|, |B| and |A and B| of a cell: as counted (columns b and n), or by its ratio and overlap."""
    return r["a"], r.get("b", r["a"] * r["size_ratio"]), r.get("n", r["a"] * r["overlap"])


def _draw(r: dict, trials: int, seed: int) -> dict:
    """Statistics of one block of trials straight from their law: multinomial case counts, gamma sums. The generator is
    seeded by (seed, cell, block), so trials do not depend on how blocks are dealt out."""
    g = np.random.default_rng([seed, r["cell"], r["block"]])
    size = min(BLOCK, trials - r["block"] * BLOCK)
    (a, b, n), m = _sizes(r), r["m"]
    u = a + b - n
    k = g.multinomial(m, [n / u, (b - n) / u, max(0.0, 1 - n / u - (b - n) / u)], size)
    su = g.gamma(m, 1.0, size) / u
    sa, sb = su + g.standard_gamma(k[:, 1]) / a, su + g.standard_gamma(k[:, 2]) / b
    return {"k_tie": k[:, 0], "k_b": k[:, 1], "k_a": k[:, 2], "k_b_seen": k[:, 1], "k_a_seen": k[:, 2], "sum_a": sa, "sum_b": sb, "sum_any": su}


def _blocks(grid: DataFrame, trials: int) -> DataFrame:
    return grid.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit((trials - 1) // BLOCK)))).repartition("cell", "block")


def simulate_stats(grid: DataFrame, trials: int, seed: int = 1) -> DataFrame:
    """One row a trial: its statistics, drawn block by block."""
    names = [x.split()[0] for x in STATS.split(", ")]
    kinds = [{"int": pa.int32(), "long": pa.int64(), "double": pa.float64()}[x.split()[1]] for x in STATS.split(", ")]

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                got = _draw(r, trials, seed)
                size = len(got["k_tie"])
                got |= {c: np.full(size, r[c]) for c in ("cell", "size_ratio", "overlap", "a", "m")} | {"trial": r["block"] * BLOCK + np.arange(size), "scale": np.ones(size)}
                yield pa.RecordBatch.from_arrays([pa.array(got[c]).cast(t) for c, t in zip(names, kinds, strict=True)], names)

    return _blocks(grid, trials).mapInArrow(run, STATS)


def simulate_accuracy(grid: DataFrame, trials: int, seed: int = 1, only: tuple = ("inclusion_exclusion", "jaccard_union", "jaccard_sum", "ml")) -> DataFrame:
    """The accuracy table of the whole experiment without a row a trial: each block of trials is drawn, estimated by all
    schemes as arrays, and leaves its count, mean and squared deviations, which are added up. Same draws and estimates
    as simulate_stats and estimate_wide."""
    out = "scheme string, size_ratio double, overlap double, m long, truth double, n long, mean double, squares double"

    def run(batches):
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                d = _draw(r, trials, seed)
                m, j = r["m"], d["k_tie"] / r["m"]
                ca, cb, cu = m / d["sum_a"], m / d["sum_b"], m / d["sum_any"]
                est = {"inclusion_exclusion": ca + cb - cu, "jaccard_union": j * cu, "jaccard_sum": j / (1 + j) * (ca + cb)}
                if "ml" in only:
                    est["ml"] = fit_arrays(*d.values())[2]
                rows += [(s, r["size_ratio"], r["overlap"], m, _sizes(r)[2], len(j), float(est[s].mean()), float(((est[s] - est[s].mean()) ** 2).sum())) for s in only]
            names = [x.split()[0] for x in out.split(", ")]
            yield pa.RecordBatch.from_pylist([dict(zip(names, x, strict=True)) for x in rows], pa.schema([(c, {"string": pa.string(), "double": pa.float64(), "long": pa.int64()}[t]) for c, t in (x.split() for x in out.split(", "))]))

    n, mean = F.col("n"), F.col("mean")
    got = _blocks(grid, trials).mapInArrow(run, out).groupBy("scheme", "size_ratio", "overlap", "m").agg(
        F.sum("n").alias("trials"), F.first("truth").alias("truth"), (F.sum(n * mean) / F.sum("n")).alias("mean"), F.sum("squares").alias("inside"), F.sum(n * (mean - F.col("truth")) * (mean - F.col("truth"))).alias("off"))
    between = F.col("off") - F.col("trials") * (F.col("mean") - F.col("truth")) * (F.col("mean") - F.col("truth"))
    return _measures(got.withColumn("var_raw", F.greatest((F.col("inside") + between) / F.col("trials"), F.lit(0.0))).drop("inside", "off"))


def simulate_registers(grid: DataFrame, trials: int, seed: int = 1) -> DataFrame:
    """Register level: each part's energy -ln(U)/size for every register; then the six sums. Built-in functions only."""
    rows = grid.withColumn("trial", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(trials - 1).cast("long")))).withColumn("k", F.explode(F.sequence(F.lit(1), F.col("m").cast("int"))))
    n, b = F.col("a") * F.col("overlap"), F.col("a") * F.col("size_ratio")
    draw = lambda size, i: F.when(size > 0, -F.ln(1.0 - F.rand(seed * 3 + i)) / size)
    rows = rows.withColumns({"ep": draw(F.col("a") - n, 0), "eq": draw(b - n, 1), "en": draw(n, 2)})
    rows = rows.withColumns({"ea": F.least("ep", "en"), "eb": F.least("eq", "en")})
    got = rows.groupBy("cell", "trial", "size_ratio", "overlap", "a", "m").agg(
        F.count_if(F.expr("ea = eb")).alias("k_tie"), F.count_if(F.expr("ea > eb")).alias("k_b"), F.count_if(F.expr("ea < eb")).alias("k_a"),
        F.sum("ea").alias("sum_a"), F.sum("eb").alias("sum_b"), F.sum(F.least("ea", "eb")).alias("sum_any"))
    return got.withColumns({"k_b_seen": F.col("k_b"), "k_a_seen": F.col("k_a"), "scale": F.lit(1.0)})


def simulate_hll(spark: SparkSession, sizes: list[float], m: int, trials: int, seed: int = 1, rank_base: int = 1) -> DataFrame:
    """(size, trial, bucket, rank) with the largest rank of a Poisson share of each size in each bucket."""
    rows = spark.createDataFrame([(float(s),) for s in sizes], "size double").withColumn("trial", F.explode(F.sequence(F.lit(0), F.lit(trials - 1)))).withColumn("bucket", F.explode(F.sequence(F.lit(0), F.lit(m - 1))))
    return rows.withColumn("rank", F.greatest(F.lit(0), F.ceil(F.log2(F.col("size") / m / -F.ln(1.0 - F.rand(seed)))) + (rank_base - 1)).cast("int"))


def hashed_hll(keys: DataFrame, elem: str, name: str, m: int, trials: int) -> DataFrame:
    """(name, trial, bucket, rank) of real hashing, two hash functions a trial: a bucket's largest rank is that of its
    smallest value, so a partition leaves trials x m minima for each set and no row an element and trial."""
    hashed = keys.select(F.col(name).alias("name"), element_hash(F.col(elem)).alias("h")).where(F.col(elem).isNotNull())
    mask, top = np.uint64((1 << 63) - 1), np.uint64((1 << 64) - 1)

    def run(batches):
        seeds, best = slot_seeds(2 * trials), {}
        for batch in batches:
            frame = batch.to_pandas()
            for who, g in frame.groupby("name"):
                h, mine = g["h"].to_numpy().view(np.uint64), best.setdefault(who, np.full((trials, m), top, np.uint64))
                for t in range(trials):
                    np.minimum.at(mine[t], ((mixed_long(h, seeds[2 * t + 1]) & mask) % np.uint64(m)).astype(np.int64), mixed_long(h, seeds[2 * t]) & mask)
        for who, mine in best.items():
            t, k = np.nonzero(mine != top)
            yield pa.RecordBatch.from_arrays([pa.array([who] * len(t)), pa.array(t.astype(np.int32)), pa.array(k.astype(np.int32)), pa.array(mine[t, k].astype(np.int64))], ["name", "trial", "bucket", "v"])

    least = hashed.mapInArrow(run, "name string, trial int, bucket int, v long").groupBy("name", "trial", "bucket").agg(F.min("v").alias("v"))
    rank = F.lit(64) - F.when(F.col("v") > 0, F.length(F.bin("v"))).otherwise(0)
    return least.select("name", "trial", "bucket", rank.cast("int").alias("rank"))


def hashed_trials(rows: DataFrame, by: list[str], m: int, trials: int) -> DataFrame:
    """Statistics of real hashing, (by..., trial): function index k of m * trials belongs to trial k div m."""
    regs = pair_registers(rows, "e", F.col("in_a"), F.col("in_b"), by, m * trials).withColumn("trial", F.floor(F.col("k") / m))
    return pair_stats(regs, [*by, "trial"], m)


def simulate_hashed(spark: SparkSession, ratio: float, overlap: float, a: int, m: int, trials: int) -> DataFrame:
    """Generated keys, hashed for real: A = [0, a), B = [a - n, a - n + ratio a). Costs keys x m x trials hashes: small a only."""
    n = int(round(overlap * a))
    top = a - n + int(round(ratio * a))
    e = F.col("e")
    rows = spark.range(max(a, top)).toDF("e").select("e", (e < a).alias("in_a"), ((e >= a - n) & (e < top)).alias("in_b"))
    return hashed_trials(rows, [], m, trials)


def accuracy_table(trials: DataFrame) -> DataFrame:
    """From (scheme, size_ratio, overlap, m, truth, estimate): mean, bias, variance (population), squared error, raw and
    divided by the truth; divided measures are null where the truth is 0."""
    got = trials.groupBy("scheme", "size_ratio", "overlap", "m").agg(F.count("*").alias("trials"), F.first("truth").alias("truth"), F.avg("estimate").alias("mean"), F.var_pop("estimate").alias("var_raw"))
    return _measures(got)


def _measures(got: DataFrame) -> DataFrame:
    t = F.col("truth")
    per = lambda x: F.try_divide(x, t)
    bias = F.abs(F.col("mean") - t)
    got = got.withColumns({"bias_norm": per(bias), "var_norm": per(per(F.col("var_raw"))), "mse": bias * bias + F.col("var_raw")})
    return got.withColumns({"rmse": F.sqrt("mse"), "mse_norm": per(per(F.col("mse"))), "rmse_norm": F.sqrt(per(per(F.col("mse"))))})


def with_theory(accuracy: DataFrame, a: float | DataFrame) -> DataFrame:
    """Adds crb_norm (the bound), theory_norm (the scheme's own law) and efficiency (bound over variance), for |A| = a, or
    for the counted sizes a, b, n of a grid; null where the truth is 0."""
    if isinstance(a, DataFrame):
        cell, names = ["size_ratio", "overlap", "m"], accuracy.columns
        counted = accuracy.join(F.broadcast(a.select(*cell, *[F.col(c).alias(f"{c}_") for c in ("a", "b", "n")])), cell)  # a row a cell
        x, b, n = F.col("a_"), F.col("b_"), F.nullif(F.col("n_"), F.lit(0.0))
        return _with_laws(counted, x, b, n).drop("a_", "b_", "n_").select(*names, "crb_norm", "theory_norm", "efficiency")
    x = F.lit(float(a))
    return _with_laws(accuracy, x, x * F.col("size_ratio"), F.nullif(x * F.col("overlap"), F.lit(0.0)))


def _with_laws(accuracy: DataFrame, x: Column, b: Column, n: Column) -> DataFrame:
    m = F.col("m").cast("double")
    law = F.when(F.col("scheme") == "inclusion_exclusion", theory.var_scheme1(x, b, n, m)).when(F.col("scheme") == "jaccard_union", theory.var_scheme2(x, b, n, m))
    law = law.when(F.col("scheme") == "jaccard_sum", theory.var_scheme3(x, b, n, m)).otherwise(theory.crb_intersection(x, b, n, m))
    crb = F.try_divide(theory.crb_intersection(x, b, n, m), n * n)
    return accuracy.withColumns({"crb_norm": crb, "theory_norm": F.try_divide(law, n * n), "efficiency": F.try_divide(crb, F.col("var_norm"))})


def improvement_table(accuracy: DataFrame) -> DataFrame:
    """Relative variance improvement of ml over each other scheme: (var_i - var_ml) / var_i."""
    wide = accuracy.groupBy("size_ratio", "overlap", "m").pivot("scheme", ["inclusion_exclusion", "jaccard_union", "jaccard_sum", "ml"]).agg(F.first("var_raw"))
    rows = F.explode(F.array(*[F.struct(F.lit(s).alias("scheme"), F.try_divide(F.col(s) - F.col("ml"), F.col(s)).alias("rel_var_improvement")) for s in ("inclusion_exclusion", "jaccard_union", "jaccard_sum")]))
    return wide.select("size_ratio", "overlap", "m", rows.alias("r")).select("size_ratio", "overlap", "m", "r.scheme", "r.rel_var_improvement")


def theory_table(grid: DataFrame) -> DataFrame:
    """Bound and scheme variances of n-hat / n, times m, by variant."""
    a = F.col("a")
    b, n, m = a * F.col("size_ratio"), a * F.col("overlap"), F.col("m").cast("double")
    norm = lambda v: F.try_divide(v * m, n * n)
    return grid.select("size_ratio", "overlap", "m", norm(theory.crb_intersection(a, b, n, m)).alias("bound"), *[norm(theory.var_scheme1(a, b, n, m, v)).alias(f"scheme1_{v}") for v in ("direct", "printed")],
                       norm(theory.var_scheme2(a, b, n, m)).alias("scheme2"), *[norm(theory.var_scheme3(a, b, n, m, v)).alias(f"scheme3_{v}") for v in ("shared", "lemma")], norm(theory.var_scheme3(a, b, n, m, "printed")).alias("scheme3_printed"))


def dominance_check(improvement: DataFrame, slack: float = 0.0) -> DataFrame:
    return improvement.groupBy("scheme", "m").agg(F.bool_and(F.coalesce(F.col("rel_var_improvement") >= -slack, F.lit(True))).alias("dominates"))


def coverage(estimates: DataFrame, by: list[str] | tuple = ()) -> DataFrame:
    """by..., share of estimates whose interval holds the truth."""
    return estimates.groupBy(*by).agg(F.avg(F.expr("cast(truth between ci_lo and ci_hi as double)")).alias("coverage"))
