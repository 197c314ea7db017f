"""Bags (bag_id, elem, weight) from tables, texts, vectors and JSON; bag algebra; exact similarities."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def aggregate_bags(rows: DataFrame, policy: str = "sum", together: bool = False) -> DataFrame:
    """One row for each (bag_id, elem): weights summed, or their maximum.

    With ``together`` the raw rows are dealt by bag, so nothing that is grouped by bag later on needs a further shuffle: a
    signature's draws are many times as many as the rows they come from. For bags that fit a task, such as a customer's.
    """
    merge = {"sum": F.sum, "max": F.max}[policy]
    if together:
        rows = rows.repartition("bag_id")
    return rows.groupBy("bag_id", "elem").agg(merge("weight").alias("weight"))


def bag_from_table(df: DataFrame, bag_id, elem, weight=1.0, policy: str = "sum", together: bool = False) -> DataFrame:
    column = lambda c: c if isinstance(c, Column) else F.col(c) if isinstance(c, str) else F.lit(c)
    rows = df.select(column(bag_id).cast("long").alias("bag_id"), column(elem).cast("long").alias("elem"), column(weight).cast("double").alias("weight"))
    return aggregate_bags(rows.where("bag_id is not null and elem is not null and weight is not null"), policy, together)


def hash_elements(*columns) -> Column:
    """Elements of any type as 64-bit ids."""
    return F.xxhash64(*columns)


def customer_part(spark: SparkSession, sf_dir: str, weight: str = "l_quantity") -> DataFrame:
    orders = load(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    lines = load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey", weight])
    return bag_from_table(lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")), "o_custkey", "l_partkey", weight, together=True)


def supplier_part(spark: SparkSession, sf_dir: str, weight=None) -> DataFrame:
    return bag_from_table(load(spark, sf_dir, "lineitem"), "l_suppkey", "l_partkey", weight if weight is not None else "l_quantity")


def revenue() -> Column:
    return F.col("l_extendedprice") * (1 - F.col("l_discount"))


def order_part(spark: SparkSession, sf_dir: str, weight="l_quantity") -> DataFrame:
    return bag_from_table(load(spark, sf_dir, "lineitem"), "l_orderkey", "l_partkey", weight, together=True)


def order_part_set(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bag_from_table(load(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"]), "l_orderkey", "l_partkey", 1.0, "max", together=True)


def words(text) -> Column:
    """Lower-case runs of ASCII letters and digits."""
    return F.regexp_extract_all(F.lower(text), F.lit(r"[a-z0-9]+"), F.lit(0))


def strip_tags(html) -> Column:
    return F.regexp_replace(F.regexp_replace(html, r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " "), r"<[^>]*>", " ")


def shingles(tokens: Column, k: int) -> Column:
    """Runs of k tokens, joined by spaces; the whole sequence when it is shorter."""

    def runs(t):  # t is a lambda's variable, so the tokens are made once and not for each run
        whole = F.transform(F.sequence(F.lit(1), F.greatest(F.size(t) - k + 1, F.lit(1))), lambda i: F.array_join(F.slice(t, i, k), " "))
        return F.when(F.size(t) > 0, whole).otherwise(F.array().cast("array<string>"))

    return F.element_at(F.transform(F.array(tokens), runs), 1)


def terms(df: DataFrame, bag_id: str, text: str, unit: str = "word", k: int = 5) -> DataFrame:
    """(bag_id, term, n): term counts of each text."""
    tokens = words(F.col(text))
    unit_array = tokens if unit == "word" else shingles(tokens, k)
    rows = df.where(F.col(text).isNotNull()).select(F.col(bag_id).cast("long").alias("bag_id"), F.explode(unit_array).alias("term"))
    return rows.groupBy("bag_id", "term").agg(F.count("*").alias("n"))


def bag_from_text(df: DataFrame, bag_id: str, text: str, unit: str = "word", k: int = 5, weight: str = "tf") -> DataFrame:
    """Bags of words or k-word shingles with weight binary, tf or tfidf (tf times ln of documents over document frequency)."""
    counted = terms(df, bag_id, text, unit, k)
    if weight == "tfidf":
        n = counted.agg(F.count_distinct("bag_id").alias("n_docs"))
        df_counts = counted.groupBy("term").agg(F.count("*").alias("df"))
        joined = counted.join(df_counts, "term").crossJoin(F.broadcast(n))  # one row
        counted = joined.withColumn("w", F.col("n") * F.log(F.col("n_docs") / F.col("df"))).where("w > 0")
    else:
        counted = counted.withColumn("w", F.lit(1.0) if weight == "binary" else F.col("n").cast("double"))
    return counted.select("bag_id", F.xxhash64("term").alias("elem"), F.col("w").alias("weight"))


#: Whole bags in an Arrow batch, and its bytes, at the most: it lies in the executor's memory and in its Python worker's at once.
BATCH_ROWS, BATCH_BYTES = 200, 4 << 20


def _small_batches(spark: SparkSession) -> None:
    """Lowers the session's Arrow batch sizes to ours where they are larger."""
    for name, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        have = spark.conf.get(f"spark.sql.execution.arrow.{name}", None)
        size = int(have) if have is not None and have.lstrip("-").isdigit() else None
        if size is not None and (size <= 0 or size > most):
            spark.conf.set(f"spark.sql.execution.arrow.{name}", str(most))


def whole_bags_from_text(df: DataFrame, bag_id: str, text: str, unit: str = "word", k: int = 5, weight: str = "tf") -> DataFrame:
    """The bags of ``bag_from_text`` with weight binary or tf, as rows (bag_id, items) in order of elements.

    Terms are hashed and counted where the text lies, without a shuffle, unless texts share an id.
    """
    if weight not in ("binary", "tf"):
        raise ValueError(f"no weight {weight} without a shuffle")
    _small_batches(df.sparkSession)

    def count(batches):
        for batch in batches:
            for start in range(0, batch.num_rows, 1000):
                part = batch.slice(start, 1000)
                lists = part.column("elems")
                bag = np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))
                elem = lists.flatten().to_numpy(zero_copy_only=False)
                order = np.lexsort((elem, bag))
                bag, elem = bag[order], elem[order]
                first = np.flatnonzero(np.concatenate(([True], (bag[1:] != bag[:-1]) | (elem[1:] != elem[:-1]))))
                n = np.diff(np.append(first, len(bag))).astype(float) if weight == "tf" else np.ones(len(first))
                ends = np.append(0, np.cumsum(np.bincount(bag[first], minlength=len(lists)))).astype(np.int32)
                rows = pa.ListArray.from_arrays(pa.array(ends), pa.StructArray.from_arrays([pa.array(elem[first]), pa.array(n)], ["elem", "weight"]))
                yield pa.RecordBatch.from_arrays([part.column("bag_id"), rows], ["bag_id", "items"])

    tokens = words(F.col(text))
    unit_array = tokens if unit == "word" else shingles(tokens, k)
    texts = df.where(F.col(text).isNotNull() & F.col(bag_id).isNotNull())
    rows = texts.select(F.col(bag_id).cast("long").alias("bag_id"), F.transform(unit_array, lambda t: F.xxhash64(t)).alias("elems")).where(F.size("elems") > 0)
    if not texts.groupBy(bag_id).count().where("count > 1").isEmpty():
        rows = rows.groupBy("bag_id").agg(F.flatten(F.collect_list("elems")).alias("elems"))
    return rows.mapInArrow(count, "bag_id long, items array<struct<elem:long,weight:double>>")


def bag_from_vector(df: DataFrame, bag_id: str, vector: str) -> DataFrame:
    """Signed vectors as bags over twice the dimensions: 2 i for a positive part, 2 i + 1 for a negative one."""
    rows = df.select(F.col(bag_id).cast("long").alias("bag_id"), F.posexplode(vector).alias("i", "v"))
    return rows.where("v <> 0").select("bag_id", (F.col("i") * 2 + (F.col("v") < 0).cast("int")).cast("long").alias("elem"), F.abs("v").cast("double").alias("weight"))


def bag_from_json(df: DataFrame, bag_id: str, json: str, path: str, weight=1.0) -> DataFrame:
    """Elements are the values of one JSON path."""
    value = F.get_json_object(json, path)
    w = F.lit(float(weight)) if isinstance(weight, (int, float)) else F.col(weight)
    return bag_from_table(df.where(value.isNotNull()).select(F.col(bag_id).alias("b"), F.xxhash64(value).alias("e"), w.alias("w")), "b", "e", "w")


def totals(bags: DataFrame) -> DataFrame:
    return bags.groupBy("bag_id").agg(F.sum("weight").alias("total"), F.count("*").alias("n"))


def nest(bags: DataFrame) -> DataFrame:
    return bags.groupBy("bag_id").agg(F.array_sort(F.collect_list(F.struct("elem", "weight"))).alias("items"))


def unnest(nested: DataFrame) -> DataFrame:
    return nested.select("bag_id", F.inline("items"))


def whole(bags: DataFrame) -> DataFrame:
    """Bags as rows (bag_id, items), if they aren't yet."""
    return bags if "items" in bags.columns else nest(bags)


def loose(bags: DataFrame) -> DataFrame:
    """Bags as rows (bag_id, elem, weight), if they aren't yet."""
    return unnest(bags) if "items" in bags.columns else bags


#: Ids that are sent to the tasks, eight bytes each; more are joined.
IDS = 1 << 22


def only(rows: DataFrame, ids: DataFrame, keep: bool = True) -> DataFrame:
    """Rows whose bag_id is among ``ids`` (distinct bag_ids), or isn't. Up to ``IDS`` ids go to the rows, so that whole bags and signatures aren't shuffled."""
    if ids.count() > IDS:
        return rows.join(ids, "bag_id", "left_semi" if keep else "left_anti")
    sent = rows.sparkSession.sparkContext.broadcast(np.sort(ids.toArrow().column(0).to_numpy().astype(np.int64)))

    def run(batches):
        known = sent.value
        for batch in batches:
            own = batch.column("bag_id").to_numpy(zero_copy_only=False)
            among = known[np.minimum(np.searchsorted(known, own), len(known) - 1)] == own if len(known) else np.zeros(len(own), bool)
            yield batch.filter(pa.array(among == keep))

    return rows.where("bag_id is not null").mapInArrow(run, rows.schema)


def ids_of(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.explode(F.array("a", "b")).alias("bag_id")).distinct()


def to_map(bags: DataFrame) -> DataFrame:
    return bags.groupBy("bag_id").agg(F.map_from_entries(F.collect_list(F.struct("elem", "weight"))).alias("w"))


# --- bag algebra: two tables of bags, matched by bag_id ---------------------------------------------------------------


def _both(a: DataFrame, b: DataFrame, how: str) -> DataFrame:
    left, right = a.withColumnRenamed("weight", "wa"), b.withColumnRenamed("weight", "wb")
    rows = left.join(right, ["bag_id", "elem"], how)
    return rows.withColumns({"wa": F.coalesce("wa", F.lit(0.0)), "wb": F.coalesce("wb", F.lit(0.0))})


def bag_union(a: DataFrame, b: DataFrame) -> DataFrame:
    """Element-wise maximum; min-merging signatures gives the same bag's signature."""
    return aggregate_bags(a.select("bag_id", "elem", "weight").unionByName(b.select("bag_id", "elem", "weight")), "max")


def bag_intersect(a: DataFrame, b: DataFrame) -> DataFrame:
    return _both(a, b, "inner").select("bag_id", "elem", F.least("wa", "wb").alias("weight"))


def bag_sum(a: DataFrame, b: DataFrame) -> DataFrame:
    return aggregate_bags(a.select("bag_id", "elem", "weight").unionByName(b.select("bag_id", "elem", "weight")))


def bag_symdiff(a: DataFrame, b: DataFrame) -> DataFrame:
    return _both(a, b, "full").select("bag_id", "elem", F.abs(F.col("wa") - F.col("wb")).alias("weight")).where("weight > 0")


def bag_scale(bags: DataFrame, factor: float) -> DataFrame:
    return bags.withColumn("weight", F.col("weight") * factor)


def bag_normalise(bags: DataFrame) -> DataFrame:
    """Weights that sum to 1 in each bag."""
    return bags.join(totals(bags).select("bag_id", "total"), "bag_id").select("bag_id", "elem", (F.col("weight") / F.col("total")).alias("weight"))


# --- exact similarities of given pairs (a, b) -------------------------------------------------------------------------


def overlap(bags: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, shared, shared_weight): elements in common and the sum of minima; pairs without any stay out."""
    left = pairs.join(bags.select(F.col("bag_id").alias("a"), "elem", F.col("weight").alias("wa")), "a")
    both = left.join(bags.select(F.col("bag_id").alias("b"), "elem", F.col("weight").alias("wb")), ["b", "elem"])
    return both.groupBy("a", "b").agg(F.count("*").alias("shared"), F.sum(F.least("wa", "wb")).alias("shared_weight"))


def jaccard_exact(bags: DataFrame, pairs: DataFrame, weighted: bool = True) -> DataFrame:
    """(a, b, j): sum of minima over sum of maxima, the latter from the totals; null when both bags are empty."""
    size = bags.groupBy("bag_id").agg((F.sum("weight") if weighted else F.count("*").cast("double")).alias("size"))
    common = overlap(bags, pairs).select("a", "b", (F.col("shared_weight") if weighted else F.col("shared").cast("double")).alias("c"))
    rows = pairs.join(common, ["a", "b"], "left")
    rows = rows.join(size.select(F.col("bag_id").alias("a"), F.col("size").alias("sa")), "a", "left").join(size.select(F.col("bag_id").alias("b"), F.col("size").alias("sb")), "b", "left")
    c, union = F.coalesce("c", F.lit(0.0)), F.coalesce("sa", F.lit(0.0)) + F.coalesce("sb", F.lit(0.0))
    return rows.select("a", "b", F.when(union > 0, c / F.when(union > 0, union - c)).alias("j"))


def jaccard_distance(bags: DataFrame, pairs: DataFrame, weighted: bool = True) -> DataFrame:
    return jaccard_exact(bags, pairs, weighted).select("a", "b", (1 - F.col("j")).alias("distance"))


def jaccard_fullouter(bags: DataFrame, pairs: DataFrame) -> DataFrame:
    """The same from both sums in one full outer join of the pairs' elements."""
    left = pairs.join(bags.select(F.col("bag_id").alias("a"), "elem", F.col("weight").alias("wa")), "a")
    right = pairs.join(bags.select(F.col("bag_id").alias("b"), "elem", F.col("weight").alias("wb")), "b")
    both = left.join(right, ["a", "b", "elem"], "full")
    wa, wb = F.coalesce("wa", F.lit(0.0)), F.coalesce("wb", F.lit(0.0))
    return both.groupBy("a", "b").agg((F.sum(F.least(wa, wb)) / F.sum(F.greatest(wa, wb))).alias("j"))


def jaccard_map(a, b) -> Column:
    """Weighted Jaccard of two map<elem, weight> columns, without a shuffle."""
    merged = F.map_values(F.map_zip_with(a, b, lambda _, x, y: F.struct(F.coalesce(x, F.lit(0.0)).alias("x"), F.coalesce(y, F.lit(0.0)).alias("y"))))
    low = F.aggregate(merged, F.lit(0.0), lambda s, v: s + F.least(v["x"], v["y"]))
    high = F.aggregate(merged, F.lit(0.0), lambda s, v: s + F.greatest(v["x"], v["y"]))
    return low / high


def neighbour_pairs(bags: DataFrame, gap: int = 1) -> DataFrame:
    """(a, b) of each bag and the bag ``gap`` ids on: a linear set of pairs over all bags."""
    ids = bags.select("bag_id").distinct()
    return ids.select(F.col("bag_id").alias("a"), (F.col("bag_id") + gap).alias("b")).join(ids.select(F.col("bag_id").alias("b")), "b", "left_semi").select("a", "b")


def wjaccard_all_pairs(bags: DataFrame) -> DataFrame:
    """Every pair of bags that share an element, by an inverted-index self-join: the ground truth for small sets."""
    left, right = bags.select(F.col("bag_id").alias("a"), "elem", F.col("weight").alias("wa")), bags.select(F.col("bag_id").alias("b"), "elem", F.col("weight").alias("wb"))
    common = left.join(right, "elem").where("a < b").groupBy("a", "b").agg(F.sum(F.least("wa", "wb")).alias("c"))
    size = totals(bags)
    rows = common.join(size.select(F.col("bag_id").alias("a"), F.col("total").alias("ta")), "a").join(size.select(F.col("bag_id").alias("b"), F.col("total").alias("tb")), "b")
    return rows.select("a", "b", (F.col("c") / (F.col("ta") + F.col("tb") - F.col("c"))).alias("j"))


def similar_pairs(bags: DataFrame, tau: float) -> DataFrame:
    """(a, b, j): every pair of bags of positive weights whose similarity reaches tau, exactly, without listing all that share an element.

    Elements are put in one order, frequent ones last. What two such bags share weighs tau of either's total or more, so the first
    element they share has that much of the bag left, itself included; only elements that have are matched, and only where
    what is left on both sides and the totals still allow tau. A bag must fit a task.
    """
    from wsig.operators.lsh import settle
    from wsig.operators.prefix import meeting_pairs

    bags = whole(bags)
    pairs = settle(meeting_pairs(bags, tau))
    return jaccard_exact(loose(only(bags, ids_of(pairs))), pairs).where(F.col("j") >= tau)


def sparsity(bags: DataFrame) -> DataFrame:
    """(bag_id, s): total weight over the total of every element's largest weight in any bag."""
    bound = bags.groupBy("elem").agg(F.max("weight").alias("top")).agg(F.sum("top").alias("bound"))
    return totals(bags).crossJoin(F.broadcast(bound)).select("bag_id", (F.col("total") / F.col("bound")).alias("s"))  # one row


def top_elements(bags: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("bag_id").orderBy(F.desc("weight"), "elem")
    return bags.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def weight_profile(bags: DataFrame) -> DataFrame:
    """Extremes and quantiles of the weights, for choosing a ladder."""
    q = F.percentile_approx("weight", F.array(F.lit(0.01), F.lit(0.5), F.lit(0.99)), 10000)
    return bags.agg(F.count("*").alias("n"), F.min("weight").alias("low"), F.max("weight").alias("high"), q.alias("quantiles"), F.approx_count_distinct("elem").alias("elements"))
