"""Pairs of bags with known similarity, and mean squared errors of estimates held against theory."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wsig.functions.estimate import expected_mse, var_mse
from wsig.functions.ladder import BinaryLadder, FloatLadder, IntegerLadder
from wsig.functions.prng import Prng
from wsig.operators import baselines, poisson
from wsig.operators.lp_kernel import sig_lp_arrow
from wsig.operators.lsh import settle

# Weights in the first and second bag, with the number of such elements, and the similarity.
CASES = {
    "V1": ([(1, 10, 1)], 0.1),
    "V2": ([(9, 10, 1)], 0.9),
    "V3": ([(3, 20, 1), (30, 7, 1)], 0.2),
    "V4": ([(0, 2, 1), (3, 4, 1), (6, 3, 1), (2, 4, 1)], 0.5),
    "V5": ([(4, 2, 15), (1, 4, 10), (12, 0, 5)], 0.25),
    "V6": ("powers", 0.538307852),
    "V7": ([(0, 1, 1), (1, 0, 1), (1, 1, 1)], 1 / 3),
    "V8": ([(0, 1, 30), (1, 0, 10), (1, 1, 160)], 0.8),
    "V9": ([(0, 1, 300), (1, 0, 500), (1, 1, 1200)], 0.6),
}


def case_weights(case: str) -> list[tuple[float, float]]:
    rows = CASES[case][0]
    if rows == "powers":
        return [(1.001**i, 1.002**i) for i in range(1001)]
    return [(float(a), float(b)) for a, b, n in rows for _ in range(n)]


def case_pairs(spark: SparkSession, case: str, n_pairs: int) -> DataFrame:
    """(bag_id, elem, weight): bag 2 p and 2 p + 1 are pair p; elements are random 64-bit ids of their own for each pair."""
    weights = spark.createDataFrame([(k, a, b) for k, (a, b) in enumerate(case_weights(case))], "k long, wa double, wb double")
    rows = spark.range(n_pairs).withColumnRenamed("id", "pair").crossJoin(F.broadcast(weights))  # a case has at most 2000 elements
    elem = F.xxhash64(F.lit(case), "pair", "k")
    sides = F.explode(F.array(F.struct((F.col("pair") * 2).alias("bag_id"), F.col("wa").alias("weight")), F.struct((F.col("pair") * 2 + 1).alias("bag_id"), F.col("wb").alias("weight"))))
    return rows.select(elem.alias("elem"), sides.alias("s")).select("s.bag_id", "elem", "s.weight").where("weight > 0")


def exact_case_jaccard(weights: DataFrame) -> DataFrame:
    """(case, j): sum of minima over sum of maxima of each case's weights (case, wa, wb)."""
    return weights.groupBy("case").agg((F.sum(F.least("wa", "wb")) / F.sum(F.greatest("wa", "wb"))).alias("j"))


BINARY = ("V7", "V8", "V9")
DEFAULT = ("lp", "lp_binary", "icws", "zero_bit", "ccws", "pcws", "i2cws")


def all_cases(spark: SparkSession, cases: list[str], n_pairs: int) -> DataFrame:
    """The bags of several cases in one table: case number i has bags from 2 i n_pairs on."""
    parts = [case_pairs(spark, c, n_pairs).withColumn("bag_id", F.col("bag_id") + 2 * i * n_pairs) for i, c in enumerate(cases)]
    return reduce(DataFrame.unionByName, parts)


def algorithms(prng: Prng | None = None) -> dict:
    """Name to (function of bags and m, whether the first components of a larger signature are a smaller one)."""
    prng = prng or Prng()
    return {
        "lp": (lambda b, m: sig_lp_arrow(b, m, IntegerLadder(30)), False),  # without rounding error where weights are integral
        "lp_float32": (lambda b, m: sig_lp_arrow(b, m, FloatLadder(32)), False),
        "lp_binary": (lambda b, m: poisson.sig_ordered(b, m, BinaryLadder(), prng), False),
        "icws": (lambda b, m: baselines.sig_icws(b, m, prng), True),
        "zero_bit": (lambda b, m: baselines.sig_icws(b, m, prng, keep="element"), True),
        "ccws": (lambda b, m: baselines.sig_ccws(b, m, prng), True),
        "pcws": (lambda b, m: baselines.sig_pcws(b, m, prng), True),
        "i2cws": (lambda b, m: baselines.sig_i2cws(b, m, prng), True),
    }


def pair_estimates(sig: DataFrame, m: int) -> DataFrame:
    """(pair, est): share of equal components of bags 2 p and 2 p + 1; every pair of non-empty bags has a row."""
    rows = sig.where(F.col("j") < m).select(F.shiftright("bag_id", 1).alias("pair"), "j", "id")
    cells = rows.groupBy("pair", "j").agg(F.count("*").alias("n"), F.min("id").alias("lo"), F.max("id").alias("hi"))
    same = ((F.col("n") == 2) & (F.col("lo") == F.col("hi"))).cast("int")
    return cells.groupBy("pair").agg((F.sum(same) / m).alias("est"))


def mse_of(est: DataFrame, cases: list[str], alg: str, m: int, n_pairs: int) -> DataFrame:
    """A row for each case: mean squared error, bias, what theory expects and the z-score of the difference."""
    table = [(i, c, CASES[c][1], expected_mse(CASES[c][1], m), var_mse(CASES[c][1], m, n_pairs)) for i, c in enumerate(cases)]
    known = F.broadcast(est.sparkSession.createDataFrame(table, "number long, case string, j_true double, expected double, variance double"))  # nine rows at most
    rows = est.withColumn("number", F.floor(F.col("pair") / n_pairs).cast("long")).join(known, "number")
    off = F.col("est") - F.col("j_true")
    sums = rows.groupBy("case", "expected", "variance").agg(F.count("*").alias("n_pairs"), F.avg(off * off).alias("mse"), F.avg(off).alias("bias"))
    return sums.select("case", F.lit(alg).alias("alg"), F.lit(m).alias("m"), "n_pairs", "mse", "expected", "bias", ((F.col("mse") - F.col("expected")) / F.sqrt("variance")).alias("z"))


def mse_table(spark: SparkSession, cases: list[str], sizes: list[int], n_pairs: int, algs: list[str] | None = None) -> DataFrame:
    """(case, alg, m, n_pairs, mse, expected, bias, z) for every cell; all cases go through one plan for each algorithm and size."""
    parts = []
    for name, (run, prefix) in algorithms().items():
        own = [c for c in cases if (c in BINARY or name != "lp_binary") and (c != "V6" or name != "lp")]
        if name not in (algs or DEFAULT) or not own:
            continue
        bags = all_cases(spark, own, n_pairs)
        whole = settle(run(bags, max(sizes))) if prefix else None
        for m in sizes:
            sig = whole if prefix else run(bags, m)
            parts.append(mse_of(pair_estimates(sig, m), own, name, m, n_pairs))
    return reduce(DataFrame.unionByName, parts)


def mse_pivot(mse: DataFrame) -> DataFrame:
    """A row for each case and size, a column of z-scores for each algorithm."""
    return mse.groupBy("case", "m").pivot("alg").agg(F.first("z"))


def failing_cells(mse: DataFrame) -> DataFrame:
    """Cells and failures (absolute z over 3) by algorithm."""
    return mse.groupBy("alg").agg(F.count("*").alias("cells"), F.expr("count(*) FILTER (WHERE abs(z) > 3)").alias("failing"))


#: Pairs of a cell by how many elements a case has, so that every case fits one run; the reference took 10 000 everywhere.
GRID = ((("V1", "V2", "V3", "V4", "V7"), 300), (("V5", "V8"), 40), (("V6", "V9"), 8))
GRID_ALGS = ["lp_float32", "lp_binary", "icws", "zero_bit", "ccws", "pcws", "i2cws"]


def error_grid(spark: SparkSession, sizes: list[int], scale: float = 1.0, groups=GRID) -> DataFrame:
    """Errors of all algorithms on all cases, with ``failing`` where they are over three standard deviations from theory."""
    parts = [mse_table(spark, list(cases), sizes, max(2, int(n * scale)), GRID_ALGS) for cases, n in groups]
    return reduce(DataFrame.unionByName, parts).withColumn("failing", F.abs("z") > 3)


def component_correlation(spark: SparkSession, case: str, m: int, n_pairs: int, prng: Prng | None = None) -> DataFrame:
    """(alg, m, bias, ratio): the estimates' mean error, and their variance over that of independent components.

    A ratio over 1 means components that go together, under 1 components that balance each other.
    """
    prng = prng or Prng()
    runs = {
        "lp_binary": lambda b: poisson.sig_ordered(b, m, BinaryLadder(), prng),
        "minhash": lambda b: baselines.sig_minhash(b, m, prng),
        "one_permutation": lambda b: baselines.sig_oph(b, m, prng),
        "rotation": lambda b: baselines.sig_oph(b, m, prng, "rotation"),
        "random_fill": lambda b: baselines.sig_oph(b, m, prng, "random"),
        "rounds": lambda b: baselines.sig_roundsketch(b, m),
        "permuted": lambda b: baselines.sig_permuted(b, m),
    }
    bags, j = settle(case_pairs(spark, case, n_pairs)), CASES[case][1]
    parts = []
    for name, run in runs.items():
        est = pair_estimates(run(bags), m).agg(F.avg("est").alias("mean"), F.var_pop("est").alias("variance"))
        parts.append(est.select(F.lit(name).alias("alg"), F.lit(m).alias("m"), (F.col("mean") - j).alias("bias"), (F.col("variance") * m / (j * (1 - j))).alias("ratio")))
    return reduce(DataFrame.unionByName, parts)


def cost_by_size(spark: SparkSession, sizes: list[int], ms: list[int], reps: int = 3) -> DataFrame:
    """(variant, m, n, points, splits, words, tracker, peak, rival_words): mean work and nodes held for random bags of n elements.

    ``rival_words`` are the draws of consistent sampling, five for each element and component.
    """
    from wsig.operators.lp_kernel import lp_costs

    bags = reduce(DataFrame.unionByName, [random_bags(spark, n, reps, seed=i + 1).withColumn("bag_id", F.col("bag_id") + i * reps) for i, n in enumerate(sizes)])
    bags, parts = settle(bags), []
    for m in ms:
        for variant in ("one_pass", "two_phase"):
            cost = lp_costs(bags, m, FloatLadder(32), variant).groupBy("n").agg(F.avg("n_points").alias("points"), F.avg("n_splits").alias("splits"), F.avg("n_words").alias("words"), F.avg("n_tree_updates").alias("tracker"), F.avg("peak_nodes").alias("peak"))
            parts.append(cost.select(F.lit(variant).alias("variant"), F.lit(m).alias("m"), "n", "points", "splits", "words", "tracker", "peak", (F.col("n") * 5 * m).alias("rival_words")))
    return reduce(DataFrame.unionByName, parts)


def extrapolated(cost: DataFrame, least: int, to: list[int]) -> DataFrame:
    """(variant, m, n, words): draws for larger bags by a straight line through the sizes from ``least`` on."""
    line = cost.where(F.col("n") >= least).groupBy("variant", "m").agg(F.regr_slope("words", "n").alias("slope"), F.regr_intercept("words", "n").alias("base"))
    return line.withColumn("n", F.explode(F.array(*[F.lit(n) for n in to]))).select("variant", "m", "n", (F.col("base") + F.col("slope") * F.col("n")).alias("words"))


def ladder_costs(spark: SparkSession, eps: list[float], n: int, m: int, reps: int = 3) -> DataFrame:
    """(eps, levels, points, splits, off): work of the two-phase walk on ladders fitted to the weights, and the rounding error at most."""
    from wsig.functions.ladder import Ladder
    from wsig.operators.lp_kernel import lp_costs

    bags = settle(random_bags(spark, n, reps))
    low, high = bags.agg(F.min("weight"), F.max("weight")).first()
    parts = []
    for e in eps:
        ladder = Ladder.for_range(low, high, e)
        level = ladder.value(ladder.index(F.col("weight")))
        off = bags.agg(F.max(F.col("weight") / level - 1)).first()[0]
        cost = lp_costs(bags, m, ladder).agg(F.avg("n_points").alias("points"), F.avg("n_splits").alias("splits"))
        parts.append(cost.select(F.lit(e).alias("eps"), F.lit(ladder.top).alias("levels"), "points", "splits", F.lit(off).alias("off")))
    return reduce(DataFrame.unionByName, parts)


def random_bags(spark: SparkSession, n: int, reps: int, seed: int = 1) -> DataFrame:
    """``reps`` bags of n random elements with exponential weights."""
    p = Prng(salt=seed)
    rows = spark.range(n * reps).select((F.col("id") % reps).alias("bag_id"), F.xxhash64(F.lit(seed), "id").alias("elem"))
    return rows.withColumn("weight", -F.log(p.u01("bag_id", "elem", 1)))
