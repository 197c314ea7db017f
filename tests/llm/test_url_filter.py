from pyspark.sql import functions as F
from pyspark.sql import types as T

from wsig.llm import url_filter as U

SCHEMA = T.StructType([T.StructField("page_id", T.LongType()), T.StructField("url", T.StringType()), T.StructField("host", T.StringType()), T.StructField("key", T.StringType()), T.StructField("verdict", T.StringType())])


def brute(url, listed, rules=U.RULES):
    if url is None or "://" not in url:
        host = path = ""
    else:
        rest = url.split("://", 1)[1]
        n = min([rest.index(c) for c in "/?#" if c in rest] or [len(rest)])
        host, rest = "".join(c.lower() if c.isascii() else c for c in rest[:n]), rest[n:]
        path = rest[: min([rest.index(c) for c in "?#" if c in rest] or [len(rest)])]
    fit = [(h + p, v) for h, p, v in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    if fit:
        rule, verdict = max(fit, key=lambda x: len(x[0]))
        return host, path, rule, verdict
    bad = any(host == k or host.endswith("." + k) for k in listed)
    return host, path, None, "block" if bad else "allow"


def rows():
    urls = [None, "", "no scheme/x", "http://", "HTTP://WWW.Example.COM/en/a?x#y", "http://example.com/en", "http://example.com", "https://a.b.net/es/1", "https://net/fr/", "ftp://x?a=/en/", "x://y#z/", "http://É.NET/de/\nq", "a://b://c/d", "http://..net//", "http://" + "a." * 300 + "net/z" * 2000]
    urls += [f"http://h{i}.{d}.org/{i}" for i in range(400) for d in ("good", "evil")] + [f"https://site{i % 97}.org/p" for i in range(500)]
    return [(i, u, "clash", "clash", "clash") for i, u in enumerate([*urls, *urls[:5]])] + [(None, "http://evil.org/", None, None, None)]


def test_matches_brute_force_and_levels_are_exact(spark):
    listed = ["evil.org", "site3.org", "site50.org", "b", "absent.example"] + [f"h{i}.good.org" for i in range(0, 400, 7)]
    keys = spark.createDataFrame([(k,) for k in [*listed, None]], "key string")
    got = U.url_filter(spark.createDataFrame(rows(), SCHEMA), keys).collect()
    want = sorted(map(str, [(r[0], *brute(r[1], listed)) for r in rows()]))
    assert sorted(map(str, [(r.page_id, r.host, r.path, r.rule, r.verdict) for r in got])) == want


def test_cascade_is_exact_over_its_universe(spark):
    universe = spark.range(5000).select(F.concat(F.lit("k"), "id").alias("key"), (F.col("id") % 37 == 0).alias("listed"))
    cascade = U.build_cascade(universe)
    assert len(cascade.levels) >= 2
    assert universe.where(cascade.holds(F.col("key")) != F.col("listed")).count() == 0


def test_parts_beyond_the_size_bound_and_empty(spark, monkeypatch):
    keys = spark.createDataFrame([("evil.org",)], "key string")
    first = sorted(map(str, U.url_filter(spark.createDataFrame(rows(), SCHEMA), keys).collect()))
    monkeypatch.setattr(U, "MOST_BITS", 40)  # four parts
    assert sorted(map(str, U.url_filter(spark.createDataFrame(rows(), SCHEMA), keys).select("page_id", "host", "path", "listed", "rule", "verdict").collect())) == first
    assert U.url_filter(spark.createDataFrame([], SCHEMA), keys).count() == 0
    assert U.url_filter(spark.createDataFrame(rows(), SCHEMA), keys.limit(0)).where("listed").count() == 0
