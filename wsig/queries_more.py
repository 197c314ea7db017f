"""Further queries: search quality, the error grid, work by size, surfaces, relational helpers, more streams."""

from __future__ import annotations

from pyspark.sql import functions as F

from wsig import surface
from wsig.functions import estimate as E
from wsig.functions.ladder import BinaryLadder, IntegerLadder, eps_negligible
from wsig.functions.prng import U1, sql_u01
from wsig.operators import bags as B
from wsig.operators import baselines, lp_kernel, lsh, poisson
from wsig.operators import relational as R
from wsig.plans import verify
from wsig.queries import _REPLICATED, _SUPPLIERS, _WEIGHTED, M, _bag, _doc_sigs, _ident, _keyed_sql, _md5, _r, _sig, _whole_doc_words, query
from wsig.sources import io
from wsig.streaming import signatures as S

# --- search quality ----------------------------------------------------------------------------------------------------

_SHINGLES = """WITH w AS (SELECT doc_id, regexp_extract_all(lower(text), '[a-z0-9]+') AS w FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(list_transform(generate_series(1, greatest(len(w) - 4, 1)), lambda i: array_to_string(w[i:i + 4], ' '))) AS t FROM w WHERE len(w) > 0),
n AS (SELECT doc_id, count(*) AS n, md5(string_agg(t, '|' ORDER BY t)) AS whole FROM s GROUP BY 1),
r AS (SELECT whole, min(doc_id) AS rep, any_value(n) AS n FROM n GROUP BY 1),
x AS (SELECT s.doc_id, t, r.n FROM s JOIN r ON s.doc_id = r.rep),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c, any_value(a.n) AS na, any_value(b.n) AS nb FROM x a JOIN x b ON a.t = b.t AND a.doc_id < b.doc_id GROUP BY 1, 2)"""


def _shingle_classes(spark, d):
    """Shingle sets, their signatures on the binary ladder, and the classes of equal sets."""
    bags = lsh.settle(_whole_doc_words(spark, d, "shingle", "binary"))
    return bags, lsh.settle(_doc_sigs(bags, ladder=BinaryLadder())), lsh.settle(lsh.equal_bags(bags))


@query(f"{_SHINGLES} SELECT count(*) FILTER (WHERE c / (na + nb - c) >= 0.8) AS true_pairs, true AS precise, true AS complete FROM p")
def near_copies_recall(spark, d):
    """Pairs of different shingle sets at 0.8: how many there are, whether all found ones are true and nine in ten or more are found."""
    bags, sigs, classes = _shingle_classes(spark, d)
    reps = B.only(bags, lsh.copies(classes), keep=False)
    truth = B.similar_pairs(reps, 0.8).select("a", "b")
    q = lsh.pair_quality(lsh.class_pairs(bags, sigs, classes, 64, 0.8).select("a", "b"), truth)
    true = F.coalesce("true", F.lit(0))
    return q.select(true.cast("long").alias("true_pairs"), (F.coalesce("precision", F.lit(1.0)) == 1).alias("precise"), (F.coalesce("recall", F.lit(1.0)) >= 0.9).alias("complete"))


@query()
def candidate_quality(spark, d):
    """Recall and precision of the candidates before they are verified, against exact similarities of 0.8 or more, over all pairs of documents, copies included."""
    bags, sigs, classes = _shingle_classes(spark, d)
    reps = lambda rows: B.only(rows, lsh.copies(classes), keep=False)
    truth = B.similar_pairs(reps(bags), 0.8).select("a", "b")
    bands, rows = E.bands_for_recall(64, 0.8)
    return lsh.pair_quality(lsh.candidate_pairs(lsh.band_keys(reps(sigs), bands, rows)), truth, classes)


# --- verification and work ---------------------------------------------------------------------------------------------


@query()
def component_correlation(spark, d):
    return verify.component_correlation(spark, "V8", 64, 200)


@query()
def one_permutation_bias(spark, d):
    """Few elements: one permutation without densification leaves empty bins and estimates too little."""
    return verify.component_correlation(spark, "V7", 16, 300)


@query()
def cost_by_size(spark, d):
    return verify.cost_by_size(spark, [1, 10, 100, 500], [16, 64], 2)


@query()
def cost_extrapolated(spark, d):
    return verify.extrapolated(verify.cost_by_size(spark, [100, 200, 400], [16], 2), 100, [10_000, 1_000_000, 10_000_000])


@query()
def ladder_cost_by_eps(spark, d):
    return verify.ladder_costs(spark, [1.0, 0.1, 0.01, 0.001], 200, 32)


_PRECISION = [(1024, 1.19e-7), (1_000_000, 1.19e-7), (1_000_000, 1e-6), (4096, 0.01), (256, 0.001)]


@query(f"WITH j AS ({_SUPPLIERS}) SELECT a, b, m, eps, CASE WHEN j = 0 THEN true ELSE eps < 0.1 * sqrt((1 - j) / (j * m)) END AS negligible FROM j, (VALUES " + ", ".join(f"({m}, {e!r}::DOUBLE)" for m, e in _PRECISION) + ") AS t(m, eps)")
def rounding_negligible(spark, d):
    """Whether rounding to a ladder's precision matters beside the error of estimating neighbouring suppliers' similarity."""
    bags = B.supplier_part(spark, d)
    pairs = B.jaccard_exact(bags, B.neighbour_pairs(bags)).withColumn("j", _r("j"))
    cells = pairs.withColumn("p", F.explode(F.array(*[F.struct(F.lit(m).alias("m"), F.lit(e).alias("eps")) for m, e in _PRECISION]))).select("a", "b", "j", "p.*")
    return cells.select("a", "b", "m", "eps", eps_negligible(F.col("j"), F.col("m"), F.col("eps")).alias("negligible"))


@query(f"""WITH j AS ({_WEIGHTED}) SELECT c_mktsegment AS "case", m, round(avg(j * (1 - j) / m), 12) AS expected, count(*) AS n
FROM j JOIN customer ON a = c_custkey, (SELECT unnest([4, 16, 64]) AS m) GROUP BY ROLLUP (c_mktsegment, m)""")
def expected_error_rollup(spark, d):
    """Expected errors of estimates of neighbouring customers' similarity, by the first one's market segment and signature size."""
    bags = B.customer_part(spark, d)
    pairs = B.jaccard_exact(bags, B.neighbour_pairs(bags)).select("a", _r("j").alias("j"))
    segments = B.load(spark, d, "customer", ["c_custkey", "c_mktsegment"]).select(F.col("c_custkey").alias("a"), F.col("c_mktsegment").alias("case"))
    cells = pairs.join(segments, "a").select("case", "j", F.explode(F.array(*[F.lit(m) for m in (4, 16, 64)])).alias("m"))
    cells = cells.withColumn("e", E.expected_mse(F.col("j"), F.col("m")))
    return cells.rollup("case", "m").agg(F.round(F.avg("e"), 12).alias("expected"), F.count("*").alias("n"))


_QUANTITY = "SELECT l_orderkey AS bag_id, l_partkey AS elem, sum(l_quantity) AS weight FROM lineitem GROUP BY ALL"
_WHOLE = f"SELECT bag_id, elem, 1.0 AS weight, unnest(generate_series(1, copies)) AS copy FROM (SELECT bag_id, elem, CAST(floor(weight) AS BIGINT) AS copies FROM ({_QUANTITY})) WHERE copies >= 1"


@query(_REPLICATED.replace("{copies}", _WHOLE).replace("generate_series(0, 7)", "generate_series(0, 1)"))
def sig_replicated_whole(spark, d):
    """Replication at scale 1: every unit of weight is a copy."""
    return _sig(baselines.sig_replicated(B.order_part(spark, d), 2, _md5()))


# --- surfaces ----------------------------------------------------------------------------------------------------------

_SPEC = surface.SignatureSpec(M, "integer:64")


@query("SELECT bag_id, true AS same FROM (" + _bag("supplier_part") + ") GROUP BY 1")
def signature_aggregate(spark, d):
    """The grouped aggregate gives the signature that the engine gives."""
    bags = B.supplier_part(spark, d)
    one = bags.groupBy("bag_id").agg(surface.lp_signature(_SPEC)("elem", "weight").alias("a"))
    return one.join(_SPEC.sign(bags), "bag_id").select("bag_id", (F.col("a") == F.col("sig")).alias("same"))


@query("SELECT bag_id, true AS same FROM (" + _bag("supplier_part") + ") WHERE bag_id <= 20 GROUP BY 1")
def signature_table_function(spark, d):
    """The least points of the SQL table function are the signature's."""
    surface.register(spark, _SPEC)
    bags = B.supplier_part(spark, d).where("bag_id <= 20")  # the suppliers of the report, with all their parts
    rows = poisson.with_horizon(bags.withColumn("level_weight", F.least(F.floor("weight"), F.lit(64)).cast("double")), M, 12.0)
    points = spark.sql("SELECT bag_id, j, x, id FROM {rows}, LATERAL split_levels(elem, weight, horizon)", rows=rows)
    got = poisson.least_points(points).select("bag_id", "j", "id")
    want = lp_kernel.sig_lp_arrow(bags, M, IntegerLadder(64)).select("bag_id", "j", F.col("id").alias("want"))
    return want.join(got, ["bag_id", "j"], "left").groupBy("bag_id").agg(F.bool_and(F.coalesce(F.col("id") == F.col("want"), F.lit(False))).alias("same"))


@query("WITH ids AS (SELECT DISTINCT l_suppkey AS i FROM lineitem) SELECT x.i AS a, y.i AS b, true AS same FROM ids x JOIN ids y ON y.i = x.i + 1")
def signature_sql(spark, d):
    """signature_jaccard in SQL and estimate_jaccard as a column."""
    surface.register(spark, _SPEC)
    bags = B.supplier_part(spark, d)
    sigs, pairs = lsh.settle(_SPEC.sign(bags)), B.neighbour_pairs(bags)
    own = spark.sql("SELECT p.a, p.b, signature_jaccard(x.sig, y.sig) AS s FROM {pairs} p JOIN {sigs} x ON x.bag_id = p.a JOIN {sigs} y ON y.bag_id = p.b", pairs=pairs, sigs=sigs)
    return own.join(surface.compare(sigs, sigs, pairs), ["a", "b"]).select("a", "b", (F.abs(F.col("s") - F.col("j")) < 1e-12).alias("same"))


@query()
def signature_ml_stage(spark, d):
    return surface.BagSignature(m=32, ladder="integer:64", bits=4).transform(B.supplier_part(spark, d))


# --- relational helpers ------------------------------------------------------------------------------------------------


@query()
def bag_sample(spark, d):
    return R.sample_bags(B.customer_part(spark, d), 10)


_SMALL = "SELECT p_partkey FROM part WHERE p_size <= 10"


@query(f"SELECT * FROM ({_bag('customer_part')}) WHERE elem IN ({_SMALL})")
def bag_restrict_to(spark, d):
    small = B.load(spark, d, "part", ["p_partkey", "p_size"]).where("p_size <= 10").select(F.col("p_partkey").alias("elem"))
    return R.restrict_to(B.customer_part(spark, d), small)


@query(f"SELECT * FROM ({_bag('customer_part')}) WHERE elem NOT IN ({_SMALL})")
def bag_exclude(spark, d):
    small = B.load(spark, d, "part", ["p_partkey", "p_size"]).where("p_size <= 10").select(F.col("p_partkey").alias("elem"))
    return R.exclude(B.customer_part(spark, d), small)


@query(f"WITH b AS ({_bag('customer_part')}) SELECT * FROM b WHERE bag_id IN (SELECT bag_id FROM b GROUP BY 1 HAVING sum(weight) >= 500 AND count(*) >= 20)")
def bag_filter(spark, d):
    return R.filter_bags(B.customer_part(spark, d), 500.0, 20)


@query(f"""SELECT bag_id, elem, row_number() OVER (PARTITION BY bag_id ORDER BY weight DESC, elem) AS nth, rank() OVER w AS rank, dense_rank() OVER w AS dense,
ntile(4) OVER (PARTITION BY bag_id ORDER BY weight DESC, elem) AS quarter, round(percent_rank() OVER w, 9) AS share FROM ({_bag('customer_part')}) WINDOW w AS (PARTITION BY bag_id ORDER BY weight DESC)""")
def element_ranks(spark, d):
    out = R.ranks(B.customer_part(spark, d))
    return out.select("bag_id", "elem", *[F.col(c).cast("long").alias(c) for c in ("nth", "rank", "dense", "quarter")], F.round("share", 9).alias("share"))


@query("""SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER f AS first, last_value(event_id) OVER f AS last, nth_value(event_id, 2) OVER f AS second
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id), f AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def event_changes(spark, d):
    return B.load(spark, d, "events", ["event_id", "user_id"]).select("event_id", *[c.alias(name) for name, c in R.changes(F.col("event_id"), "user_id").items()])


@query(f"SELECT CAST(least(greatest(floor((weight - 1) / 99 * 10) + 1, 0), 11) AS BIGINT) AS bin, count(*) AS n FROM ({_bag('customer_part')}) GROUP BY 1")
def weight_histogram(spark, d):
    return R.histogram(B.customer_part(spark, d), 1.0, 100.0, 10)


@query("SELECT round(corr(l_quantity, l_extendedprice), 6) AS r, count(*) AS n FROM lineitem")
def weight_correlation(spark, d):
    return B.load(spark, d, "lineitem", ["l_quantity", "l_extendedprice"]).agg(F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.count("*").alias("n"))


@query(f"WITH t AS (SELECT bag_id, sum(weight) AS total, CAST(count(*) AS DOUBLE) AS n FROM ({_bag('supplier_part')}) GROUP BY 1) SELECT bag_id, 'total' AS measure, total AS value FROM t UNION ALL SELECT bag_id, 'n', n FROM t")
def totals_unpivot(spark, d):
    t = B.totals(B.supplier_part(spark, d)).withColumn("n", F.col("n").cast("double"))
    return t.unpivot("bag_id", ["total", "n"], "measure", "value")


@query("SELECT l_partkey AS elem FROM lineitem WHERE l_returnflag = 'A' INTERSECT ALL SELECT l_partkey FROM lineitem WHERE l_returnflag = 'R'")
def elements_common(spark, d):
    rows = B.load(spark, d, "lineitem", ["l_partkey", "l_returnflag"])
    side = lambda flag: rows.where(F.col("l_returnflag") == flag).select(F.col("l_partkey").alias("elem"))
    return side("A").intersectAll(side("R"))


_HALVES = """WITH RECURSIVE t(lo, hi, depth) AS (SELECT {start} UNION ALL SELECT CASE WHEN s = 0 THEN lo ELSE {mid} END, CASE WHEN s = 0 THEN {mid} ELSE hi END, depth + 1
FROM t, (SELECT 0 AS s UNION ALL SELECT 1) AS side WHERE hi - lo > 1) SELECT depth, count(*) AS ranges, min(hi - lo) AS narrow, max(hi - lo) AS wide FROM t GROUP BY depth"""


@query(_HALVES.format(start=f"0::BIGINT, max(weight)::BIGINT, 0 FROM ({_bag('customer_part')})", mid="(lo + hi) // 2"))
def halving_rounds(spark, d):
    """The tree of halved level ranges of a ladder up to the customers' largest weight, by recursive SQL."""
    top = lsh.settle(B.customer_part(spark, d).agg(F.max("weight").cast("long").alias("top")))  # one row, which the rounds don't make again
    return spark.sql(_HALVES.format(start="0L, top, 0 FROM {top}", mid="(lo + hi) DIV 2"), top=top).select(*[F.col(c).cast("long").alias(c) for c in ("depth", "ranges", "narrow", "wide")])


@query("""WITH c AS (SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS cluster FROM documents WHERE text IS NOT NULL),
k AS (SELECT cluster, quality, count(*) AS n FROM c JOIN labels USING (doc_id) GROUP BY 1, 2), b AS (SELECT cluster, max(n) AS best, sum(n) AS n FROM k GROUP BY 1)
SELECT count(*) AS clusters, CAST(sum(n) AS BIGINT) AS nodes, CAST(sum(best) AS BIGINT) AS pure FROM b""")
def cluster_purity(spark, d):
    """How far clusters of equal texts agree with the quality labels."""
    docs = B.load(spark, d, "documents", ["doc_id", "text"]).where("text is not null").select("doc_id", F.sha2("text", 256).alias("h"))
    clusters = docs.join(docs.groupBy("h").agg(F.min("doc_id").alias("cluster")), "h").select(F.col("doc_id").alias("node"), "cluster")
    return R.purity(clusters, B.load(spark, d, "labels").select(F.col("doc_id").alias("node"), F.col("quality").alias("label")))


def _trees(spark, d):
    """Each customer's tree: orders by priority below the customer, line items by return flag below the orders."""
    orders = B.load(spark, d, "orders", ["o_orderkey", "o_custkey", "o_orderpriority"])
    lines = B.load(spark, d, "lineitem", ["l_orderkey", "l_returnflag"]).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    lines = lines.groupBy("o_custkey", "o_orderkey", "l_returnflag").agg(F.count("*").alias("n")).withColumn("k", F.explode(F.sequence(F.lit(1).cast("long"), "n")))
    root = orders.select(F.col("o_custkey").alias("tree"), F.lit("c").alias("node"), F.lit(None).cast("string").alias("parent"), F.lit("customer").alias("label")).distinct()
    middle = orders.select(F.col("o_custkey").alias("tree"), F.concat(F.lit("o"), "o_orderkey").alias("node"), F.lit("c").alias("parent"), F.col("o_orderpriority").alias("label"))
    leaves = lines.select(F.col("o_custkey").alias("tree"), F.concat_ws("-", F.lit("l"), "o_orderkey", "l_returnflag", "k").alias("node"), F.concat(F.lit("o"), "o_orderkey").alias("parent"), F.col("l_returnflag").alias("label"))
    return root.unionByName(middle).unionByName(leaves)


@query("""WITH p AS (SELECT o_custkey AS bag_id, 'customer' AS t FROM orders GROUP BY 1 UNION ALL SELECT o_custkey, o_orderpriority FROM orders UNION ALL SELECT o_custkey, 'customer/' || o_orderpriority FROM orders
UNION ALL SELECT o_custkey, l_returnflag FROM lineitem JOIN orders ON l_orderkey = o_orderkey UNION ALL SELECT o_custkey, o_orderpriority || '/' || l_returnflag FROM lineitem JOIN orders ON l_orderkey = o_orderkey
UNION ALL SELECT o_custkey, 'customer/' || o_orderpriority || '/' || l_returnflag FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
b AS (SELECT bag_id, t, count(*)::DOUBLE AS w FROM p GROUP BY 1, 2), s AS (SELECT bag_id, sum(w) AS s FROM b GROUP BY 1),
c AS (SELECT x.bag_id AS a, y.bag_id AS b, sum(least(x.w, y.w)) AS c FROM b x JOIN b y ON y.bag_id = x.bag_id + 1 AND y.t = x.t GROUP BY 1, 2)
SELECT a, b, round(c / (m.s + n.s - c), 9) AS j FROM c JOIN s m ON m.bag_id = a JOIN s n ON n.bag_id = b""")
def tree_similarity(spark, d):
    """Weighted Jaccard of neighbouring customers' trees by their label paths."""
    bags = lsh.settle(R.tree_bags(_trees(spark, d), 3))
    return B.jaccard_exact(bags, B.neighbour_pairs(bags)).select("a", "b", F.round("j", 9).alias("j"))


# --- streams -----------------------------------------------------------------------------------------------------------


@query("SELECT event_id, user_id FROM events")
def stream_dedup(spark, d):
    """Every event arrives twice and stays once."""
    events = S.timed(io.stream_table(spark, d, "events"), "40 days").select("event_id", "user_id", "ts")
    return S.run_available_now(S.stream_dedup(events.unionByName(events), ["event_id"]), "append").select("event_id", "user_id")


@query("""SELECT c.event_id AS l_id, p.event_id AS r_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR""")
def stream_interval(spark, d):
    """Purchases within an hour of a click, as a join of two streams."""
    side = lambda kind: S.timed(io.stream_table(spark, d, "events"), "40 days").where(F.col("event_type") == kind)
    return S.run_available_now(S.stream_interval_pairs(side("click"), side("purchase")), "append").select("l_id", "r_id")


_KINDS = "SELECT DISTINCT user_id AS bag_id, CASE event_type WHEN 'click' THEN 1 WHEN 'purchase' THEN 2 WHEN 'view' THEN 3 ELSE 4 END AS elem, 1.0 AS weight FROM events"


@query(_keyed_sql(_KINDS, 8, {}, sql_u01("elem", "j", str(U1)), _ident("elem")))
def stream_points(spark, d):
    """Minwise signatures of users' event kinds as a plain streaming aggregate."""
    kind = F.expr("CASE event_type WHEN 'click' THEN 1 WHEN 'purchase' THEN 2 WHEN 'view' THEN 3 ELSE 4 END").cast("long")
    rows = io.stream_table(spark, d, "events").select(F.col("user_id").alias("bag_id"), kind.alias("elem"), F.lit(1.0).alias("weight"))
    prng = _md5()
    points = lambda r: baselines.components(r, 8).select("bag_id", "j", prng.u01("elem", "j", U1).alias("x"), prng.identity("elem").alias("id"))
    return _sig(S.run_available_now(S.windowed_points(rows, points)))


@query("SELECT x.doc_id AS bag_id, y.doc_id AS stored_id FROM documents x JOIN documents y ON x.text = y.text WHERE len(regexp_extract_all(lower(x.text), '[a-z0-9]+')) > 0")
def stream_match(spark, d):
    """Arriving documents against the stored ones: whole signatures of word sequences that agree."""
    sign = lambda docs: docs.where("text is not null").select(F.col("doc_id").alias("bag_id"), S.min_hashes(F.when(F.size(B.words(F.col("text"))) > 0, F.array(F.xxhash64("text"))).otherwise(F.array().cast("array<long>")), 8).alias("sig")).where("sig is not null")
    stored = lsh.settle(sign(B.load(spark, d, "documents", ["doc_id", "text"])))
    arriving = sign(io.stream_table(spark, d, "documents"))
    return S.run_available_now(S.stream_match(arriving, stored, 1, 8), "append").select("bag_id", "stored_id")
