"""Workloads of the operators, sources, sinks, functions and streams around the methods."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from corpuskit.functions import udfs
from corpuskit.functions.tokens import round6
from corpuskit.operators import relational as R
from corpuskit.plans import licensing
from corpuskit.registry import register
from corpuskit.sources import adapters as A
from corpuskit.sources import tables as T
from corpuskit.streaming import ops as S


def t(spark, sf_dir, name):
    return T.read_table(spark, sf_dir, name)


def _scratch(spark):
    return T.scratch_path(spark, "workload")


# ---------------------------------------------------------------------- sources and sinks


@register("scan_parquet", "SELECT o_orderpriority, count(*) AS n FROM orders WHERE o_totalprice > 100000 GROUP BY 1")
def scan_parquet(spark, sf_dir):
    return t(spark, sf_dir, "orders").filter("o_totalprice > 100000").groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@register("roundtrip_jsonl", "SELECT doc_id, lang, source, length(text)::BIGINT AS n FROM documents")
def roundtrip_jsonl(spark, sf_dir):
    path = _scratch(spark)
    T.write(t(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source"), path, "json", compression="gzip")
    manifest = T.release_manifest(spark, path).filter("file like 'part-%'")
    back = T.read_release(spark, manifest, path, "doc_id long, text string, lang string, source string")
    return back.select("doc_id", "lang", "source", F.length("text").cast("long").alias("n"))


@register("roundtrip_csv", "SELECT c_custkey, c_name, c_acctbal FROM customer")
def roundtrip_csv(spark, sf_dir):
    path = _scratch(spark)
    c = t(spark, sf_dir, "customer").select("c_custkey", "c_name", "c_acctbal")
    T.write(c, path, "csv", header="true")
    return T.read(spark, path, "csv", c.schema, header="true")


@register("roundtrip_orc_partitioned", "SELECT o_orderstatus, count(*) AS n FROM orders GROUP BY 1")
def roundtrip_orc(spark, sf_dir):
    path = _scratch(spark)
    T.write(t(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus"), path, "orc", ("o_orderstatus",))
    return T.read(spark, path, "orc").groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@register("text_wholetext", "SELECT 1::BIGINT AS files, count(*) AS lines FROM nation")
def wholetext(spark, sf_dir):
    path = _scratch(spark)
    t(spark, sf_dir, "nation").select("n_name").coalesce(1).write.text(path)
    w = spark.read.text(path, wholetext=True)
    return w.agg(F.count("*").alias("files"), F.sum(F.size(F.split(F.trim(F.regexp_replace("value", r"\n+$", "")), "\n"))).alias("lines"))


@register("paged_license_source", f"SELECT corpus_id, service, raw FROM ({A.REPORTS_SQL})")
def paged(spark, sf_dir):
    """The paginated lookup over all ids of the documents, which are numbered from 0."""
    spark.dataSource.register(T.PagedLicenses)
    ids = t(spark, sf_dir, "documents").select(F.col("doc_id").alias("corpus_id"))
    last = ids.agg(F.coalesce(F.max("corpus_id") + 1, F.lit(0)).alias("n")).first()["n"]
    found = spark.read.format("paged_licenses").option("rows", str(last)).load()
    return found.join(ids, "corpus_id", "left_semi")


@register("release_check", "SELECT CASE WHEN i < 2 THEN 'changed' WHEN i = 2 THEN 'missing' WHEN i = 3 THEN 'extra' ELSE 'intact' END AS status, count(*) AS n FROM range(8) t(i) GROUP BY 1")
def release_check(spark, sf_dir):
    """A pinned release of eight files against a copy in which two entries differ, one file is gone and one is new."""
    path = _scratch(spark)
    t(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice").repartition(7).write.json(path)
    files = T.release_manifest(spark, path).filter("file like 'part-%'").withColumn("i", F.expr("cast(substr(file, 6, 5) as int)"))
    pinned = files.filter("i <> 3").select(F.when(F.col("i") < 2, F.sha2("sha256", 256)).otherwise(F.col("sha256")).alias("sha256"), "file", "bytes")
    gone = pinned.limit(1).select("sha256", F.lit("part-lost.json").alias("file"), "bytes")
    found = T.check_release(spark, pinned.unionByName(gone), path).filter("file like 'part-%'")
    return found.groupBy("status").agg(F.count("*").alias("n"))


@register("ingest_bucketed", f"WITH papers AS ({A.PAPERS_SQL}) SELECT corpus_id, title, length(text)::BIGINT AS n_chars FROM papers JOIN documents ON doc_id = corpus_id")
def ingest_bucketed(spark, sf_dir):
    """Papers and texts as bucketed tables; joining them on the id needs no exchange."""
    name = uuid.uuid4().hex
    papers = T.ingest(A.papers(spark, sf_dir).select("corpus_id", "title"), f"papers_{name}", path=_scratch(spark))
    texts = T.ingest(t(spark, sf_dir, "documents").select(F.col("doc_id").alias("corpus_id"), "text"), f"texts_{name}", path=_scratch(spark))
    return papers.hint("merge").join(texts, "corpus_id").select("corpus_id", "title", F.length("text").cast("long").alias("n_chars"))


# ------------------------------------------------------------------------------- filters


@register("filter_eligible", "SELECT doc_id FROM documents WHERE n_chars >= 1000 AND lang IN ('en', 'fr') AND source LIKE 'src1%'")
def filter_eligible(spark, sf_dir):
    return t(spark, sf_dir, "documents").filter((F.col("n_chars") >= 1000) & F.col("lang").isin("en", "fr") & F.col("source").like("src1%")).select("doc_id")


@register("filter_null_safe", "SELECT count(*) AS n FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.quality IS NOT DISTINCT FROM NULL")
def filter_null_safe(spark, sf_dir):
    d = t(spark, sf_dir, "documents").join(t(spark, sf_dir, "labels"), "doc_id", "left")
    return d.filter(F.col("quality").eqNullSafe(F.lit(None))).agg(F.count("*").alias("n"))


@register("filter_array_exists", "SELECT vec_id FROM embeddings WHERE len(list_filter(embedding, lambda x: x > 0.35)) > 0 AND len(list_filter(embedding, lambda x: x <= -0.4)) = 0")
def filter_array_exists(spark, sf_dir):
    return t(spark, sf_dir, "embeddings").filter(F.exists("embedding", lambda x: x > 0.35) & F.forall("embedding", lambda x: x > -0.4)).select("vec_id")


# --------------------------------------------------------------------------------- joins


@register("join_inner_align", "SELECT o_orderkey, c_name FROM orders JOIN customer ON o_custkey = c_custkey")
def join_inner(spark, sf_dir):
    o, c = t(spark, sf_dir, "orders"), t(spark, sf_dir, "customer")
    return R.join_equi(o, c, o.o_custkey == c.c_custkey, hint="merge").select("o_orderkey", "c_name")


@register("join_broadcast", "SELECT s_suppkey, n_name FROM supplier JOIN nation ON s_nationkey = n_nationkey")
def join_broadcast(spark, sf_dir):
    s, n = t(spark, sf_dir, "supplier"), t(spark, sf_dir, "nation")
    return R.join_equi(s, n, s.s_nationkey == n.n_nationkey, hint="broadcast").select("s_suppkey", "n_name")


@register("join_shuffle_hash", "SELECT l_orderkey, count(*) AS n FROM lineitem JOIN part ON p_partkey = l_partkey WHERE p_size < 10 GROUP BY 1")
def join_shuffle_hash(spark, sf_dir):
    l, p = t(spark, sf_dir, "lineitem"), t(spark, sf_dir, "part").filter("p_size < 10")
    return R.join_equi(l, p, l.l_partkey == p.p_partkey, hint="shuffle_hash").groupBy("l_orderkey").agg(F.count("*").alias("n"))


@register("join_full_outer_ids", "SELECT coalesce(a.doc_id, b.doc_id) AS id, a.doc_id IS NOT NULL AS a, b.doc_id IS NOT NULL AS b FROM (SELECT doc_id FROM documents WHERE lang = 'en') a FULL JOIN labels b ON a.doc_id = b.doc_id")
def join_full(spark, sf_dir):
    a = t(spark, sf_dir, "documents").filter("lang = 'en'").select(F.col("doc_id").alias("x"))
    b = t(spark, sf_dir, "labels").select(F.col("doc_id").alias("y"))
    return a.join(b, a.x == b.y, "full").select(F.coalesce("x", "y").alias("id"), F.col("x").isNotNull().alias("a"), F.col("y").isNotNull().alias("b"))


@register("join_semi", "SELECT doc_id FROM documents SEMI JOIN labels USING (doc_id)")
def join_semi(spark, sf_dir):
    return R.join_equi(t(spark, sf_dir, "documents").select("doc_id"), t(spark, sf_dir, "labels"), "doc_id", "left_semi")


@register("join_anti", "SELECT doc_id FROM documents ANTI JOIN labels USING (doc_id)")
def join_anti(spark, sf_dir):
    return R.join_equi(t(spark, sf_dir, "documents").select("doc_id"), t(spark, sf_dir, "labels"), "doc_id", "left_anti")


@register("join_right", "SELECT l.doc_id, d.lang FROM (SELECT * FROM documents WHERE lang = 'en') d RIGHT JOIN labels l ON d.doc_id = l.doc_id")
def join_right(spark, sf_dir):
    return R.join_equi(t(spark, sf_dir, "documents").filter("lang = 'en'").select("doc_id", "lang"), t(spark, sf_dir, "labels").select("doc_id"), "doc_id", "right")


@register("join_cross_queries", "SELECT count(*) AS n FROM embeddings e, embeddings q WHERE q.vec_id % 100 = 0")
def join_cross(spark, sf_dir):
    e = t(spark, sf_dir, "embeddings").select("vec_id")
    return e.crossJoin(F.broadcast(e.filter("vec_id % 100 = 0").withColumnRenamed("vec_id", "q"))).agg(F.count("*").alias("n"))


@register("join_theta", "SELECT r.r_name, count(*) AS n FROM supplier s JOIN region r ON s.s_suppkey % 5 >= r.r_regionkey GROUP BY 1")
def join_theta(spark, sf_dir):
    return R.join_theta(t(spark, sf_dir, "supplier"), t(spark, sf_dir, "region"), F.expr("s_suppkey % 5 >= r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@register("join_contains", A.DOC_GOLD_SQL)
def join_contains(spark, sf_dir):
    return R.join_contains(t(spark, sf_dir, "documents").select("doc_id", "text"), t(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("passage")))


@register("join_range_spans", "SELECT o_orderkey, b.lo FROM orders JOIN (SELECT k * 7000 AS lo, k * 7000 + 5000 AS hi FROM range(60) t(k)) b ON o_totalprice >= lo AND o_totalprice < hi")
def join_range(spark, sf_dir):
    b = spark.range(60).select((F.col("id") * 7000).alias("lo"), (F.col("id") * 7000 + 5000).alias("hi"))
    o = t(spark, sf_dir, "orders").select("o_orderkey", F.col("o_totalprice").alias("p"))
    return R.join_range(o, b, 4000).select("o_orderkey", "lo")


@register("join_interval_events", "SELECT v.event_id AS view_id, p.event_id AS buy_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR")
def join_interval(spark, sf_dir):
    e = t(spark, sf_dir, "events")
    v = e.filter("event_type = 'view'").select("user_id", F.col("ts").alias("vt"), F.col("event_id").alias("view_id"))
    p = e.filter("event_type = 'purchase'").select("user_id", F.col("ts").alias("pt"), F.col("event_id").alias("buy_id"))
    return R.join_interval(v, p, "user_id", "vt", "pt", "1 HOUR").select("view_id", "buy_id")


@register("join_asof", "WITH p AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'), s AS (SELECT user_id, ts, max(event_id) AS sid FROM events WHERE event_type = 'signup' GROUP BY ALL) SELECT p.event_id, s.sid AS last_signup FROM p ASOF LEFT JOIN s ON p.user_id = s.user_id AND p.ts >= s.ts")
def join_asof(spark, sf_dir):
    e = t(spark, sf_dir, "events")
    p = e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts")
    s = e.filter("event_type = 'signup'").groupBy("user_id", F.col("ts").alias("st")).agg(F.max("event_id").alias("sid"))
    return R.join_asof(p, s, ["user_id"], "ts", "st", "sid").select("event_id", F.col("asof_sid").alias("last_signup"))


@register("join_lateral", "SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents")
def join_lateral(spark, sf_dir):
    return T.sql(spark, sf_dir, r"SELECT doc_id, line FROM {documents}, LATERAL explode(split(text, '\n')) AS x(line)")


_LINES = "l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents), c AS (SELECT line, count(*) AS n FROM l GROUP BY line)"


@register("join_salted", f"WITH {_LINES} SELECT doc_id, line, n FROM l JOIN c USING (line) WHERE n > 1")
def join_salted(spark, sf_dir):
    l = t(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    return R.join_salted(l, l.groupBy("line").agg(F.count("*").alias("n")).filter("n > 1"), "line").select("doc_id", "line", "n")


# -------------------------------------------------------------------------- aggregations


@register("agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, floor(sum(l_quantity) * 100 + 0.5) / 100 AS qty, min(l_shipdate) AS first FROM lineitem GROUP BY 1, 2")
def agg_hash(spark, sf_dir):
    return R.agg(t(spark, sf_dir, "lineitem"), ["l_returnflag", "l_linestatus"], n=F.count("*"), qty=F.floor(F.sum("l_quantity") * 100 + 0.5) / 100, first=F.min("l_shipdate"))


@register("agg_money_decimal", "SELECT o_orderstatus, sum(o_totalprice::DECIMAL(12,2))::DECIMAL(22,2) AS total FROM orders GROUP BY 1")
def agg_decimal(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.sum(F.col("o_totalprice").cast("decimal(12,2)")).alias("total"))


@register("agg_distinct", "SELECT lang, count(DISTINCT source) AS sources, count(DISTINCT n_chars) AS lengths FROM documents GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return t(spark, sf_dir, "documents").groupBy("lang").agg(F.count_distinct("source").alias("sources"), F.count_distinct("n_chars").alias("lengths"))


_GROUP = "SELECT o_orderstatus, o_orderpriority, grouping_id(o_orderstatus, o_orderpriority)::INT AS gid, count(*) AS n FROM orders GROUP BY {g}"


@register("agg_rollup", _GROUP.format(g="ROLLUP (o_orderstatus, o_orderpriority)"))
def agg_rollup(spark, sf_dir):
    return R.grouping(t(spark, sf_dir, "orders"), "rollup", ["o_orderstatus", "o_orderpriority"], n=F.count("*"))


@register("agg_cube", _GROUP.format(g="CUBE (o_orderstatus, o_orderpriority)"))
def agg_cube(spark, sf_dir):
    return R.grouping(t(spark, sf_dir, "orders"), "cube", ["o_orderstatus", "o_orderpriority"], n=F.count("*"))


@register("agg_grouping_sets", _GROUP.format(g="GROUPING SETS ((o_orderstatus), (o_orderpriority), ())"))
def agg_sets(spark, sf_dir):
    return T.sql(spark, sf_dir, "SELECT o_orderstatus, o_orderpriority, CAST(grouping_id(o_orderstatus, o_orderpriority) AS INT) AS gid, count(*) AS n FROM {orders} GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")


@register("agg_pivot", "SELECT lang, count(*) FILTER (k = 0) AS a, count(*) FILTER (k = 1) AS b FROM (SELECT lang, doc_id % 3 AS k FROM documents) GROUP BY lang")
def agg_pivot(spark, sf_dir):
    d = t(spark, sf_dir, "documents").withColumn("k", F.when(F.col("doc_id") % 3 == 0, "a").when(F.col("doc_id") % 3 == 1, "b").otherwise("c"))
    return R.pivot(d, "lang", "k", ["a", "b"], F.count(F.lit(1))).na.fill(0)


@register("agg_unpivot", "SELECT o_orderkey, 'price' AS name, o_totalprice AS v FROM orders UNION ALL SELECT o_orderkey, 'key', o_custkey::DOUBLE FROM orders")
def agg_unpivot(spark, sf_dir):
    o = t(spark, sf_dir, "orders").select("o_orderkey", F.col("o_totalprice").alias("price"), F.col("o_custkey").cast("double").alias("key"))
    return o.unpivot("o_orderkey", ["price", "key"], "name", "v")


@register("agg_max_by", "SELECT lang, arg_max(doc_id, n_chars * 100000 + doc_id) AS longest, arg_min(doc_id, n_chars * 100000 + doc_id) AS shortest FROM documents GROUP BY 1")
def agg_max_by(spark, sf_dir):
    k = F.col("n_chars") * 100000 + F.col("doc_id")
    return t(spark, sf_dir, "documents").groupBy("lang").agg(F.max_by("doc_id", k).alias("longest"), F.min_by("doc_id", k).alias("shortest"))


@register("agg_listagg", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def agg_listagg(spark, sf_dir):
    return T.sql(spark, sf_dir, "SELECT n_regionkey, listagg(n_name, ',') WITHIN GROUP (ORDER BY n_name) AS names FROM {nation} GROUP BY n_regionkey")


@register("agg_corr", "SELECT floor(corr(l_quantity, l_extendedprice) * 10000 + 0.5) / 10000 AS r, floor(stddev_samp(l_quantity) * 10000 + 0.5) / 10000 AS s FROM lineitem")
def agg_corr(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").agg((F.floor(F.corr("l_quantity", "l_extendedprice") * 10000 + 0.5) / 10000).alias("r"), (F.floor(F.stddev_samp("l_quantity") * 10000 + 0.5) / 10000).alias("s"))


@register("agg_percentile", "SELECT o_orderstatus, quantile_cont(o_custkey, 0.25) AS q1, quantile_cont(o_custkey, 0.9) AS q9 FROM orders GROUP BY 1")
def agg_percentile(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(F.percentile("o_custkey", 0.25).alias("q1"), F.percentile("o_custkey", 0.9).alias("q9"))


@register("agg_filter", "SELECT count(*) FILTER (quality = 1) AS good, count(*) FILTER (toxic = 1) AS toxic, bool_and(quality IS NOT NULL) AS complete FROM labels")
def agg_filter(spark, sf_dir):
    return t(spark, sf_dir, "labels").agg(F.count_if(F.col("quality") == 1).alias("good"), F.count_if(F.col("toxic") == 1).alias("toxic"), F.bool_and(F.col("quality").isNotNull()).alias("complete"))


@register("agg_mode", "SELECT lang, arg_max(source, n * 1000 - i) AS mode FROM (SELECT lang, source, count(*) AS n, substr(source, 4)::INT AS i FROM documents GROUP BY ALL) GROUP BY lang")
def agg_mode(spark, sf_dir):
    g = t(spark, sf_dir, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"))
    return g.groupBy("lang").agg(F.max_by("source", F.col("n") * 1000 - F.substring("source", 4, 10).cast("int")).alias("mode"))


@register("agg_sketches")
def agg_sketches(spark, sf_dir):
    return R.sketches(t(spark, sf_dir, "events"), ["event_type"], "user_id")


@register("agg_approx_top_k")
def agg_approx_top(spark, sf_dir):
    return T.sql(spark, sf_dir, "SELECT inline(approx_top_k(source, 5)) FROM {documents}")


@register("agg_kll")
def agg_kll(spark, sf_dir):
    return T.sql(spark, sf_dir, "SELECT lang, kll_sketch_get_quantile_bigint(kll_sketch_agg_bigint(n_chars), CAST(0.5 AS DOUBLE)) AS median FROM {documents} GROUP BY lang")


# ------------------------------------------------------------------------------- windows


@register("win_rank", "SELECT c_custkey, rank() OVER w AS r, dense_rank() OVER w AS d FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY floor(c_acctbal / 1000))")
def win_rank(spark, sf_dir):
    c = t(spark, sf_dir, "customer")
    o = [F.floor(F.col("c_acctbal") / 1000)]
    return R.rank_within(R.rank_within(c, ["c_mktsegment"], o, "rank", "r"), ["c_mktsegment"], o, "dense_rank", "d").select("c_custkey", "r", "d")


@register("win_ntile", "SELECT c_custkey, ntile(4) OVER w AS q, floor(percent_rank() OVER w * 1000000 + 0.5) / 1000000 AS p, floor(cume_dist() OVER w * 1000000 + 0.5) / 1000000 AS c FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_custkey)")
def win_ntile(spark, sf_dir):
    w = Window.partitionBy("c_mktsegment").orderBy("c_custkey")
    return t(spark, sf_dir, "customer").select("c_custkey", F.ntile(4).over(w).alias("q"), round6(F.percent_rank().over(w)).alias("p"), round6(F.cume_dist().over(w)).alias("c"))


@register("win_lag_lead", "SELECT event_id, lag(event_id) OVER w AS prev, lead(event_id, 2) OVER w AS next2, nth_value(event_id, 3) OVER w AS third FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("prev"), F.lead("event_id", 2).over(w).alias("next2"), F.nth_value("event_id", 3).over(w).alias("third"))


@register("win_last_ignore_nulls", "SELECT event_id, last_value(CASE WHEN event_type = 'signup' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM events")
def win_last(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return t(spark, sf_dir, "events").select("event_id", F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), True).over(w).alias("s"))


@register("win_rows_frame", "SELECT event_id, sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING)::BIGINT AS s FROM events")
def win_rows(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 1)
    return t(spark, sf_dir, "events").select("event_id", F.sum("event_id").over(w).alias("s"))


@register("win_range_frame", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 3 PRECEDING AND CURRENT ROW) AS n FROM part")
def win_range(spark, sf_dir):
    return R.rolling(t(spark, sf_dir, "part"), ["p_brand"], "p_size", -3, 0, "range", n=F.count("*")).select("p_partkey", "n")


@register("win_interval_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 6 HOURS PRECEDING AND CURRENT ROW) AS n FROM events")
def win_interval(spark, sf_dir):
    return T.sql(spark, sf_dir, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY CAST(ts AS TIMESTAMP) RANGE BETWEEN INTERVAL 6 HOURS PRECEDING AND CURRENT ROW) AS n FROM {events}")


# ----------------------------------------------------------------- sorts, limits, set operations


@register("sort_global", "SELECT doc_id, row_number() OVER (ORDER BY n_chars DESC, doc_id)::INT AS place FROM documents ORDER BY 2 LIMIT 20")
def sort_global(spark, sf_dir):
    d = R.top_k(t(spark, sf_dir, "documents").select("doc_id", "n_chars"), 20, F.col("n_chars").desc(), F.col("doc_id"))
    return d.withColumn("place", F.row_number().over(Window.orderBy(F.col("n_chars").desc(), "doc_id"))).select("doc_id", "place")


@register("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 15 OFFSET 30")
def limit_offset(spark, sf_dir):
    return t(spark, sf_dir, "orders").select("o_orderkey").orderBy("o_orderkey").offset(30).limit(15)


@register("topk_global", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def topk_global(spark, sf_dir):
    return R.top_k(t(spark, sf_dir, "orders"), 10, F.col("o_totalprice").desc(), F.col("o_orderkey")).select("o_orderkey")


@register("topk_per_group", "SELECT c_mktsegment, c_custkey, rank FROM (SELECT *, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey)::INT AS rank FROM customer) WHERE rank <= 3")
def topk_per_group(spark, sf_dir):
    return R.top_k_per(t(spark, sf_dir, "customer"), ["c_mktsegment"], 3, F.col("c_acctbal").desc(), F.col("c_custkey")).select("c_mktsegment", "c_custkey", "rank")


@register("set_union_by_name", "SELECT doc_id AS id, lang AS kind, NULL AS url FROM documents UNION ALL BY NAME SELECT page_id AS id, url FROM pages")
def set_union(spark, sf_dir):
    a = t(spark, sf_dir, "documents").select(F.col("doc_id").alias("id"), F.col("lang").alias("kind"))
    return a.unionByName(t(spark, sf_dir, "pages").select(F.col("page_id").alias("id"), "url"), allowMissingColumns=True)


def _ids(spark, sf_dir):
    return t(spark, sf_dir, "documents").select(F.col("doc_id").alias("id")), t(spark, sf_dir, "labels").select(F.col("doc_id").alias("id"))


@register("set_intersect", "SELECT doc_id AS id FROM documents INTERSECT SELECT doc_id FROM labels")
def set_intersect(spark, sf_dir):
    a, b = _ids(spark, sf_dir)
    return a.intersect(b)


@register("set_except", "SELECT doc_id AS id FROM documents EXCEPT SELECT doc_id FROM labels")
def set_except(spark, sf_dir):
    a, b = _ids(spark, sf_dir)
    return a.subtract(b)


@register("set_except_all", "SELECT lang FROM documents EXCEPT ALL SELECT lang FROM documents WHERE n_chars < 1000")
def set_except_all(spark, sf_dir):
    d = t(spark, sf_dir, "documents")
    return d.select("lang").exceptAll(d.filter("n_chars < 1000").select("lang"))


@register("set_intersect_all", "SELECT lang FROM documents WHERE n_chars < 1000 INTERSECT ALL SELECT d.lang FROM documents d SEMI JOIN labels USING (doc_id)")
def set_intersect_all(spark, sf_dir):
    d = t(spark, sf_dir, "documents")
    return d.filter("n_chars < 1000").select("lang").intersectAll(d.join(t(spark, sf_dir, "labels"), "doc_id", "left_semi").select("lang"))


# ----------------------------------------------------------------------------- functions


@register("fn_string", "SELECT c_custkey, upper(substr(c_name, 1, 4)) AS a, length(c_name)::INT AS n, translate(c_name, '#0', '-o') AS tr, string_split(c_name, '#')[2] AS num FROM customer")
def fn_string(spark, sf_dir):
    return t(spark, sf_dir, "customer").select("c_custkey", F.upper(F.substring("c_name", 1, 4)).alias("a"), F.length("c_name").alias("n"), F.translate("c_name", "#0", "-o").alias("tr"), F.try_element_at(F.split("c_name", "#"), F.lit(2)).alias("num"))


@register("fn_regexp", r"SELECT doc_id, len(regexp_extract_all(text, '[A-Z]\w+'))::INT AS caps, md5(regexp_replace(text, '[aeiou]', '*', 'g')) AS r, md5(lower(text)) AS m FROM documents")
def fn_regexp(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", F.regexp_count("text", F.lit(r"[A-Z]\w+")).alias("caps"), F.md5(F.regexp_replace("text", "[aeiou]", "*")).alias("r"), F.md5(F.lower("text")).alias("m"))


@register("fn_levenshtein", "SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name)::INT AS d FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def fn_levenshtein(spark, sf_dir):
    n = t(spark, sf_dir, "nation")
    a, b = n.select(F.col("n_name").alias("a"), "n_regionkey", F.col("n_nationkey").alias("i")), n.select(F.col("n_name").alias("b"), "n_regionkey", F.col("n_nationkey").alias("j"))
    return a.join(b, "n_regionkey").filter("i < j").select("a", "b", F.levenshtein("a", "b").alias("d"))


@register("fn_date", "SELECT o_orderkey, year(o_orderdate)::INT AS y, date_trunc('month', o_orderdate)::DATE AS m, (o_orderdate + INTERVAL 3 MONTH)::DATE AS later, datediff('day', DATE '1995-01-01', o_orderdate::DATE)::INT AS days FROM orders")
def fn_date(spark, sf_dir):
    d = F.col("o_orderdate")
    return t(spark, sf_dir, "orders").select("o_orderkey", F.year(d).alias("y"), F.date_trunc("month", d).cast("date").alias("m"), F.add_months(d.cast("date"), 3).alias("later"), F.datediff(d.cast("date"), F.lit("1995-01-01").cast("date")).alias("days"))


@register("fn_math", "SELECT p_partkey, floor(ln(p_retailprice) * 1000000 + 0.5) / 1000000 AS l, floor(sqrt(p_size) * 1000000 + 0.5) / 1000000 AS s, CASE WHEN p_size % 7 = 0 THEN NULL ELSE floor(p_retailprice / (p_size % 7) * 1000 + 0.5) / 1000 END AS d FROM part")
def fn_math(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", round6(F.ln("p_retailprice")).alias("l"), round6(F.sqrt("p_size")).alias("s"), (F.floor(F.try_divide(F.col("p_retailprice"), F.col("p_size") % 7) * 1000 + 0.5) / 1000).alias("d"))


@register("fn_array", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::INT AS pos, list_position(embedding, list_max(embedding))::BIGINT AS top FROM embeddings")
def fn_array(spark, sf_dir):
    return t(spark, sf_dir, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.array_position("embedding", F.array_max("embedding")).alias("top"))


@register("fn_map", "SELECT doc_id, CASE WHEN lang = 'en' THEN n_chars * 2 END AS v, 2 AS size FROM documents")
def fn_map(spark, sf_dir):
    m = F.map_from_entries(F.array(F.struct(F.col("lang").alias("k"), F.col("n_chars").alias("v")), F.struct(F.lit("all").alias("k"), F.col("n_chars").alias("v"))))
    d = t(spark, sf_dir, "documents").withColumn("m", F.transform_values(m, lambda k, v: v * 2))
    return d.select("doc_id", F.try_element_at("m", F.lit("en")).alias("v"), F.size(F.map_filter("m", lambda k, v: v >= 0)).alias("size"))


@register("fn_json_props", "SELECT event_id, (props->>'$.k')::INT AS k FROM events")
def fn_json(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@register("fn_variant", "SELECT event_id, (props->>'$.k')::INT AS k FROM events")
def fn_variant(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@register("fn_hash", "SELECT doc_id, sha256(text) AS h FROM documents")
def fn_hash(spark, sf_dir):
    return t(spark, sf_dir, "documents").select("doc_id", F.sha2("text", 256).alias("h"))


@register("udf_sql_functions", r"SELECT doc_id, len(regexp_extract_all(text, '[\p{L}\p{N}]+|[^\p{L}\p{N}\s]'))::INT AS n FROM documents")
def udf_sql(spark, sf_dir):
    return udfs.engine_sql(spark, sf_dir, "SELECT doc_id, n_tokens(text) AS n FROM {documents}")


@register("udtf_ngrams", r"SELECT p_partkey, lower(p_name) AS gram FROM part WHERE len(regexp_extract_all(p_name, '[\p{L}\p{N}]+')) = 2")
def udtf_ngrams(spark, sf_dir):
    return udfs.engine_sql(spark, sf_dir, "SELECT p_partkey, gram FROM {part}, LATERAL ngrams(p_name, 2)")


@register("udtf_chunk_text", r"""WITH n AS (SELECT doc_id, len(regexp_extract_all(text, '[\p{L}\p{N}]+|[^\p{L}\p{N}\s]')) AS n FROM documents) SELECT doc_id, c::INT AS chunk_no, least(200, n - (c - 1) * 180)::INT AS n_tokens FROM (SELECT *, unnest(range(1, greatest(ceil((n - 20) / 180)::INT, 1) + 1)) AS c FROM n WHERE n > 0)""")
def udtf_chunk(spark, sf_dir):
    return udfs.engine_sql(spark, sf_dir, "SELECT doc_id, chunk_no, n_tokens FROM {documents}, LATERAL chunk_text(text, 200, 20)")


@register("udf_encode_text")
def udf_encode(spark, sf_dir):
    return udfs.engine_sql(spark, sf_dir, "SELECT item_id, encode_text(text) AS embedding FROM {benchmark}")


@register("udaf_soft_match")
def udaf_soft_match(spark, sf_dir):
    """Mean soft-match F1 of the first line of each text against its first three, by language."""
    return udfs.engine_sql(spark, sf_dir, "SELECT lang, soft_match(split(text, '\n')[0], array_join(slice(split(text, '\n'), 1, 3), ' ')) AS f1 FROM {documents} GROUP BY lang")


@register("engine_sql_papers", "SELECT count(*) AS n FROM documents WHERE lang = 'en'")
def engine_sql_papers(spark, sf_dir):
    return udfs.engine_sql(spark, sf_dir, "SELECT count(*) AS n FROM {papers} WHERE array_contains(fields, 'en')")


# ------------------------------------------------------------------------------- streams


def _events(spark, sf_dir):
    """A file stream: every query below runs it to its end and reads back what arrived in the sink."""
    return S.read_events(spark, sf_dir)


@register("stream_tumbling", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, count(*) AS n, floor(sum(value) * 100 + 0.5) / 100 AS total FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf_dir):
    out = S.run_to_table(S.tumbling(_events(spark, sf_dir), "1 day", ["event_type"]), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n", (F.floor(F.col("total") * 100 + 0.5) / 100).alias("total"))


@register("stream_sliding", "SELECT s AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 1 DAY, ts), time_bucket(INTERVAL 1 DAY, ts) - INTERVAL 1 DAY]) AS s FROM events) GROUP BY 1, 2")
def stream_sliding(spark, sf_dir):
    out = S.run_to_table(S.sliding(_events(spark, sf_dir), "2 days", "1 day", ["event_type"]), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "event_type", "n")


@register("stream_session", """WITH b AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR > ts THEN 0 ELSE 1 END AS brk FROM events),
s AS (SELECT *, sum(brk) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM b) SELECT user_id, min(ts) AS start, count(*) AS n FROM s GROUP BY user_id, sid""")
def stream_session(spark, sf_dir):
    out = S.run_to_table(S.session(_events(spark, sf_dir), "12 hours", ["user_id"]), "complete")
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), "n")


@register("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf_dir):
    return S.run_to_table(S.dedup(_events(spark, sf_dir), ["user_id", "event_type"], "60 days").select("user_id", "event_type"))


@register("stream_static_join", "SELECT event_id, c_mktsegment FROM events LEFT JOIN customer ON c_custkey = user_id")
def stream_static(spark, sf_dir):
    c = t(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return S.run_to_table(S.enrich_static(_events(spark, sf_dir), c, "user_id").select("event_id", "c_mktsegment"))


@register("stream_stream_join", "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 2 HOUR")
def stream_stream(spark, sf_dir):
    v, p = (_events(spark, sf_dir).filter(F.col("event_type") == kind).select("user_id", F.col("event_id").alias(f"{kind}_id"), F.col("ts").alias(f"{kind[0]}t")) for kind in ("view", "purchase"))
    return S.run_to_table(S.join_streams(v, p, "user_id", "vt", "pt", "2 HOURS").select("view_id", "purchase_id"))


@register("stream_stateful_consensus", """WITH g AS (SELECT user_id * 1000 + dayofyear(ts) AS key, count(event_type) AS votes, min(event_type) AS low, max(event_type) AS high FROM events GROUP BY 1)
SELECT key, votes, CASE WHEN votes >= 2 AND low = high THEN low END AS label, CASE WHEN votes >= 2 AND low = high THEN 'label' WHEN low <> high THEN 'conflict' ELSE 'insufficient' END AS outcome FROM g""")
def stream_consensus(spark, sf_dir):
    votes = _events(spark, sf_dir).select((F.col("user_id") * 1000 + F.dayofyear("ts")).alias("key"), F.col("event_type").alias("value"))
    with S.state_store(spark):
        return S.run_to_table(S.consensus(votes), "update", ["key"])


@register("stream_late_rows", "SELECT count(*) AS arrived, count(*) FILTER (event_id % 2 = 0) AS in_time FROM events")
def stream_late_rows(spark, sf_dir):
    """The odd events arrive in a second file, two years late: all are dropped behind the watermark and reported."""
    path = _scratch(spark)
    e = t(spark, sf_dir, "events")
    for n, part in enumerate((e.filter("event_id % 2 = 0"), e.limit(0), e.filter("event_id % 2 = 1").withColumn("ts", F.col("ts") - F.expr("INTERVAL 2 YEARS")))):
        part.coalesce(1).write.parquet(f"{path}/part={n}")
    stream = S.with_time(spark.readStream.schema(S.EVENTS).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(f"{path}/part=*"))
    report = S.run_reporting(S.dedup(stream, ["event_id"], "1 hour"), _scratch(spark), _scratch(spark))
    dropped, all_ = sum(r["dropped"] for r in report), e.count()
    return spark.range(1).select(F.lit(all_).alias("arrived"), F.lit(all_ - dropped).alias("in_time"))
