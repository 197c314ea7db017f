"""Similarity search on signatures: banding, candidates, joins, neighbours, clusters, containment and kernels."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from wsig.functions.estimate import bands_for_recall, estimate_jaccard
from wsig.operators.bags import ids_of, jaccard_exact, loose, only, totals

BLOCK = 256


def shared_dir(spark: SparkSession) -> str:
    """The cluster's checkpoint folder, as a full URI; a temporary one of our own only where there is one machine."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if spark.sparkContext.master.split("[")[0] == "local":
        made = getattr(shared_dir, "made", None)
        if made is None:
            made = shared_dir.made = tempfile.mkdtemp(prefix="wsig-")
            atexit.register(shutil.rmtree, made, ignore_errors=True)
        return f"file://{made}"
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    at = jvm.org.apache.hadoop.fs.Path("wsig-scratch")
    return at.getFileSystem(conf).makeQualified(at).toString()


def settle(df: DataFrame) -> DataFrame:
    """Written and read again: the lineage ends in the shared folder."""
    path = f"{shared_dir(df.sparkSession)}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def band_keys(sigs: DataFrame, bands: int, rows: int) -> DataFrame:
    """(bag_id, band, bucket): a hash of each band's components; bags with a null component in a band stay out of it."""
    part = lambda i: F.slice("sig", i * rows + 1, rows)
    keys = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda i: F.when(~F.exists(part(i), lambda v: v.isNull()), F.xxhash64(i, part(i))))
    return sigs.select("bag_id", F.posexplode(keys).alias("band", "bucket")).where("bucket is not null")


def _pairs_within(rows: DataFrame, group: list[str]) -> DataFrame:
    """(*group, a, b) with a < b for every two ids of a group. A group of over ``BLOCK`` ids is dealt to blocks and paired
    block against block, so no task holds a large group."""
    size = rows.groupBy(*group).agg(F.count("*").alias("n")).where("n > 1").select(*group, F.ceil(F.col("n") / BLOCK).cast("int").alias("blocks"))
    dealt = rows.join(size, group).withColumn("own", F.pmod(F.xxhash64("bag_id", F.lit(11)), F.col("blocks")).cast("int"))
    left = dealt.select(*group, F.col("bag_id").alias("a"), F.col("own").alias("i"), F.explode(F.sequence(F.col("own"), F.col("blocks") - 1)).alias("j"))
    right = dealt.select(*group, F.col("bag_id").alias("b"), F.explode(F.sequence(F.lit(0), F.col("own"))).alias("i"), F.col("own").alias("j"))
    pairs = left.join(right, [*group, "i", "j"]).where("i < j OR a < b")
    return pairs.select(*group, F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))


def candidate_pairs(keys: DataFrame, max_bucket: int | None = None) -> DataFrame:
    """Distinct pairs (a, b) that share a bucket.

    ``max_bucket`` is for callers that want links rather than pairs: a bucket of over so many bags only links each of them
    to its smallest one. Those links aren't enough where candidates are verified, as one that fails takes its bag's others along.
    """
    if max_bucket is None:
        return _pairs_within(keys, ["band", "bucket"]).select("a", "b").distinct()
    sized = keys.join(keys.groupBy("band", "bucket").agg(F.count("*").alias("n"), F.min("bag_id").alias("least")), ["band", "bucket"])
    pairs = _pairs_within(sized.where(F.col("n") <= max_bucket).select("band", "bucket", "bag_id"), ["band", "bucket"]).select("a", "b")
    stars = sized.where((F.col("n") > max_bucket) & (F.col("bag_id") != F.col("least"))).select(F.col("least").alias("a"), F.col("bag_id").alias("b"))
    return pairs.unionByName(stars).distinct()


def equal_bags(bags: DataFrame) -> DataFrame:
    """(rep, bag_id): each bag and the smallest id of the bags equal to it, by 128 bits of hash and the number of elements."""
    if "items" in bags.columns:  # in order of elements
        marks = bags.select("bag_id", F.xxhash64("items").alias("x"), F.xxhash64(F.lit(1), "items").alias("y"), F.size("items").alias("n"))
    else:
        marks = bags.groupBy("bag_id").agg(F.bit_xor(F.xxhash64("elem", "weight")).alias("x"), F.bit_xor(F.xxhash64("weight", "elem", F.lit(1))).alias("y"), F.count("*").alias("n"))
    reps = marks.groupBy("x", "y", "n").agg(F.min("bag_id").alias("rep"))
    return marks.join(reps, ["x", "y", "n"]).select("rep", "bag_id")


def copies(classes: DataFrame) -> DataFrame:
    """The bags that others stand for."""
    return classes.where("rep <> bag_id").select("bag_id")


def class_pairs(bags: DataFrame, sigs: DataFrame, classes: DataFrame, m: int, tau: float, verify: bool = True) -> DataFrame:
    """(a, b, j) between the representatives of different classes of equal bags."""
    bands, rows = bands_for_recall(m, tau)
    pairs = candidate_pairs(band_keys(only(sigs, copies(classes), keep=False), bands, rows))
    size = totals(loose(bags)).select("bag_id", "total")
    pairs = pairs.join(size.select(F.col("bag_id").alias("a"), F.col("total").alias("ta")), "a").join(size.select(F.col("bag_id").alias("b"), F.col("total").alias("tb")), "b")
    pairs = settle(pairs.where(F.least("ta", "tb") >= tau * F.greatest("ta", "tb")).select("a", "b"))
    if verify:
        scored = jaccard_exact(loose(only(bags, ids_of(pairs))) if "items" in bags.columns else bags, pairs)
    else:
        scored = estimate_pairs(only(sigs, ids_of(pairs)), pairs)
    return scored.where(F.col("j") >= tau)


def similarity_join(bags: DataFrame, sigs: DataFrame, m: int, tau: float, verify: bool = True) -> DataFrame:
    """(a, b, j) of all pairs in a bucket whose exact (or estimated) similarity reaches tau; sizes that can't are dropped first.

    Equal bags are searched as one, and their pairs listed at the end.
    """
    classes = settle(equal_bags(bags))
    within = _pairs_within(classes, ["rep"]).select("a", "b", F.lit(1.0).alias("j"))
    across = class_pairs(bags, sigs, classes, m, tau, verify)
    blocks = classes.groupBy("rep").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks"))
    members = classes.join(blocks, "rep").select("rep", "bag_id", F.pmod(F.xxhash64("bag_id", F.lit(11)), F.col("blocks")).cast("int").alias("own"))
    for side in ("a", "b"):  # a block of each class at a time
        across = across.join(blocks.select(F.col("rep").alias(side), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias(f"{side}_own")), side)
    for side in ("a", "b"):
        across = across.join(members.select(F.col("rep").alias(side), F.col("own").alias(f"{side}_own"), F.col("bag_id").alias(f"{side}_id")), [side, f"{side}_own"])
    across = across.select(F.least("a_id", "b_id").alias("a"), F.greatest("a_id", "b_id").alias("b"), "j")
    return within.unionByName(across)


def similarity_links(bags: DataFrame, sigs: DataFrame, m: int, tau: float) -> DataFrame:
    """(a, b) that connect what ``similarity_join`` connects: all pairs of classes, but each equal bag only to its representative."""
    classes = settle(equal_bags(bags))
    same = classes.where("rep <> bag_id").select(F.col("rep").alias("a"), F.col("bag_id").alias("b"))
    return class_pairs(bags, sigs, classes, m, tau).select("a", "b").unionByName(same)


def estimate_pairs(sigs: DataFrame, pairs: DataFrame) -> DataFrame:
    left, right = sigs.select(F.col("bag_id").alias("a"), F.col("sig").alias("sa")), sigs.select(F.col("bag_id").alias("b"), F.col("sig").alias("sb"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", estimate_jaccard("sa", "sb").alias("j"))


def two_table_join(left: DataFrame, right: DataFrame, bands: int, rows: int) -> DataFrame:
    """(a, b) pairs of bags of two signature tables that share a bucket."""
    l, r = band_keys(left, bands, rows), band_keys(right, bands, rows)  # noqa: E741
    return l.withColumnRenamed("bag_id", "a").join(r.withColumnRenamed("bag_id", "b"), ["band", "bucket"]).select("a", "b").distinct()


def knn(sims: DataFrame, k: int) -> DataFrame:
    """The k most similar of each bag, from pairs (a, b, j) taken both ways; ties to the smaller id."""
    both = sims.select(F.col("a").alias("query"), F.col("b").alias("neighbour"), "j").unionByName(sims.select(F.col("b").alias("query"), F.col("a").alias("neighbour"), "j"))
    order = Window.partitionBy("query").orderBy(F.desc("j"), "neighbour")
    return both.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def components(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(node, cluster): the smallest node reachable. Labels fall along edges and jump to their label's label each round."""
    both = settle(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    labels = settle(nodes.select("node", F.col("node").alias("cluster")))
    while True:
        near = both.join(labels.select(F.col("node").alias("b"), F.col("cluster").alias("c")), "b").groupBy("a").agg(F.min("c").alias("c"))
        down = labels.join(near.withColumnRenamed("a", "node"), "node", "left").select("node", "cluster", F.least("cluster", F.coalesce("c", "cluster")).alias("low"))
        jump = down.select(F.col("node").alias("low"), F.col("low").alias("next"))
        new = settle(down.join(jump, "low", "left").select("node", "cluster", F.least("low", F.coalesce("next", "low")).alias("new")))
        if new.where("new < cluster").isEmpty():
            return labels
        labels = new.select("node", F.col("new").alias("cluster"))


def dedup(df: DataFrame, clusters: DataFrame, key: str, keep: str = "min_id") -> DataFrame:
    """One row of each cluster: the smallest id, or the longest text and then the smallest id."""
    order = {"min_id": [key], "longest": [F.desc(F.length("text")), key]}[keep]
    rows = df.join(clusters.withColumnRenamed("node", key), key)
    ranked = rows.withColumn("__nth", F.row_number().over(Window.partitionBy("cluster").orderBy(*order)))
    return ranked.where("__nth = 1").drop("__nth", "cluster")


def pair_quality(found: DataFrame, truth: DataFrame, classes: DataFrame | None = None) -> DataFrame:
    """Recall, precision and F1 of found pairs against true ones.

    With ``classes`` of equal bags the pairs are of representatives and the counts of all bags, without listing their pairs:
    one of representatives stands for every pair of their classes' members, and the pairs within a class are both true and
    found, as equal bags have equal signatures.
    """
    both = found.select("a", "b", F.lit(1).alias("f")).join(truth.select("a", "b", F.lit(1).alias("t")), ["a", "b"], "full")
    both = both.select("a", "b", F.coalesce("f", F.lit(0)).alias("f"), F.coalesce("t", F.lit(0)).alias("t"), F.lit(1).cast("long").alias("n"))
    if classes is not None:
        size = classes.groupBy("rep").agg(F.count("*").alias("n"))
        for side in ("a", "b"):
            both = both.join(size.select(F.col("rep").alias(side), F.col("n").alias(f"n{side}")), side)
        within = size.where("n > 1").select(F.lit(1).alias("f"), F.lit(1).alias("t"), F.expr("n * (n - 1) div 2").alias("n"))
        both = both.select("f", "t", (F.col("na") * F.col("nb")).alias("n")).unionByName(within)
    count = lambda c: F.sum(c * F.col("n"))
    n = both.agg(count(F.col("f")).alias("found"), count(F.col("t")).alias("true"), F.coalesce(count(F.col("f") * F.col("t")), F.lit(0)).alias("hit"))
    recall, precision = F.try_divide("hit", "true"), F.try_divide("hit", "found")
    return n.select("found", "true", "hit", recall.alias("recall"), precision.alias("precision"), F.try_divide(2 * recall * precision, recall + precision).alias("f1"))


def asymmetric_pad(bags: DataFrame, common) -> DataFrame:
    """Data bags padded by a private element to a common weight (a number, or a column of ``total``), so that similarity to a query grows with their overlap."""
    goal = common if isinstance(common, Column) else F.lit(float(common))
    pad = totals(bags).select("bag_id", F.xxhash64(F.lit("pad"), "bag_id").alias("elem"), (goal - F.col("total")).alias("weight")).where("weight > 0")
    return bags.select("bag_id", "elem", "weight").unionByName(pad)


#: Queries and bags of one tile of ``search``.
QUERY_BLOCK, BAG_BLOCK = 256, 4096


def _tile(queries: pa.Table, bags: pa.Table, keep: int | None, slack: float) -> pa.Table:
    """Similarities of a block of queries and a block of bags, an element at a time."""
    if not queries.num_rows or not bags.num_rows:  # a side without rows comes without columns
        return pa.table({"a": np.zeros(0, np.int64), "b": np.zeros(0, np.int64), "j": np.zeros(0)})
    get = lambda t, c: t.column(c).to_numpy()
    q_ids, q = np.unique(get(queries, "bag_id"), return_inverse=True)
    n_ids, n = np.unique(get(bags, "b_id"), return_inverse=True)
    wq, wn, eq, en = get(queries, "weight"), get(bags, "b_weight"), get(queries, "elem"), get(bags, "b_elem")
    common, share = np.zeros((len(q_ids), len(n_ids))), np.zeros((len(q_ids), len(n_ids)), bool)
    oq, on = np.argsort(eq, kind="stable"), np.argsort(en, kind="stable")
    elems = np.intersect1d(eq, en)
    cuts = [np.searchsorted(e[o], elems, side) for e, o in ((eq, oq), (en, on)) for side in ("left", "right")]
    for a, b, c, d in zip(*(x.tolist() for x in cuts)):
        i, k = oq[a:b], on[c:d]
        at = np.ix_(q[i], n[k])
        common[at] += np.minimum.outer(wq[i], wn[k])
        share[at] = True
    share &= q_ids[:, None] != n_ids[None, :]
    union = np.bincount(q, wq)[:, None] + np.bincount(n, wn)[None, :] - common
    j = np.divide(common, union, out=np.full(common.shape, np.nan), where=union > 0)
    if keep is not None and len(n_ids) > keep:  # rounding may tie what lies this near, so that stays as well
        held = np.where(share, j, -1.0)
        share &= held >= np.partition(held, len(n_ids) - keep, axis=1)[:, len(n_ids) - keep, None] - slack
    i, k = np.nonzero(share)
    return pa.table({"a": q_ids[i], "b": n_ids[k], "j": j[i, k]})


def search(bags: DataFrame, queries: Column, keep: int | None = None, slack: float = 1e-5) -> DataFrame:
    """(a, b, j): the weighted Jaccard similarity of each bag a that ``queries`` (a condition on bag_id) names to every other bag that shares an element.

    Blocks of queries meet blocks of bags in numpy, so pairs of rows are never shuffled. With ``keep`` a block gives each query's
    nearest so many and whatever lies within ``slack`` of them.
    """
    bags = settle(bags.select("bag_id", "elem", "weight"))
    ids = bags.select("bag_id").distinct().agg(F.count("*").alias("n"), F.count(F.when(queries, 1)).alias("q")).first()
    nb, qb = max(1, -(-ids["n"] // BAG_BLOCK)), max(1, -(-ids["q"] // QUERY_BLOCK))
    block = lambda n: F.pmod(F.xxhash64("bag_id", F.lit(17)), F.lit(n)).cast("int")
    spread = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = bags.where(queries).withColumn("qb", block(qb)).withColumn("nb", spread(nb))
    right = bags.withColumn("nb", block(nb)).withColumn("qb", spread(qb)).select(*[F.col(a).alias(b) for a, b in (("bag_id", "b_id"), ("elem", "b_elem"), ("weight", "b_weight"), ("qb", "b_qb"), ("nb", "b_nb"))])
    return left.groupBy("qb", "nb").cogroup(right.groupBy("b_qb", "b_nb")).applyInArrow(lambda x, y: _tile(x, y, keep, slack), "a long, b long, j double")


def nearest(sims: DataFrame, k: int) -> DataFrame:
    """The k most similar bags of each query, from rows (a, b, j) of queries a; ties to the smaller id."""
    order = Window.partitionBy("query").orderBy(F.desc("j"), "neighbour")
    rows = sims.select(F.col("a").alias("query"), F.col("b").alias("neighbour"), "j")
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def minmax_kernel(bags: DataFrame) -> DataFrame:
    """(a, b, k): sum of minima over sum of maxima for every pair of bags that share an element."""
    from wsig.operators.bags import wjaccard_all_pairs

    return wjaccard_all_pairs(bags).withColumnRenamed("j", "k")


def one_hot_features(sigs: DataFrame, bits: int, dims: int = 1 << 16) -> DataFrame:
    """(bag_id, feature): b-bit components as one-hot hashed features for linear learners."""
    from wsig.functions.estimate import bbit

    return sigs.select("bag_id", F.posexplode(bbit("sig", bits)).alias("j", "v")).select("bag_id", F.pmod(F.xxhash64("j", "v"), F.lit(dims)).alias("feature"))


def size_ratio(ta: Column, tb: Column) -> Column:
    """An upper bound of similarity from totals alone."""
    return F.least(ta, tb) / F.greatest(ta, tb)


def size_ratio_pairs(total: DataFrame, tau: float) -> DataFrame:
    """Pairs of bags whose totals allow tau, by geometric bins of the total: each bin meets itself and the next."""
    import math

    step = math.log(1 / tau)
    binned = total.withColumn("bin", F.floor(F.log("total") / step).cast("long"))
    left = binned.select(F.col("bag_id").alias("a"), F.col("total").alias("ta"), F.explode(F.array(F.col("bin") - 1, F.col("bin"), F.col("bin") + 1)).alias("bin"))
    right = binned.select(F.col("bag_id").alias("b"), F.col("total").alias("tb"), "bin")
    return left.join(right, "bin").where("a < b").where(size_ratio(F.col("ta"), F.col("tb")) >= tau).select("a", "b")
