"""The surrounding operators on the given tables, each with its oracle."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from tilesieve.functions.sizing import plan_filter
from tilesieve.functions.text import detokenize, normalize, page_language, page_text, tokenize_punct
from tilesieve.operators import bloom, joins
from tilesieve.plans import oracle as o
from tilesieve.sources.io import load_table, rejoin_lines

Query = Callable[[SparkSession, str], DataFrame]
REGISTRY: dict[str, tuple[Query, str | None]] = {}


def query(sql: str | None = None):
    def add(f: Query) -> Query:
        REGISTRY[f.__name__] = f, sql
        return f

    return add


def t(s: SparkSession, d: str, name: str) -> DataFrame:
    return load_table(s, d, name)


def r2(c, places: int = 2):
    return F.round(c, places)


# -- sources and projections -------------------------------------------------------------------


@query("SELECT doc_id, lang, source, n_chars, length(text) AS chars FROM documents")
def scan_parquet(s, d):
    return t(s, d, "documents").select("doc_id", "lang", "source", "n_chars", F.length("text").cast("bigint").alias("chars"))


@query("SELECT vec_id, label, len(embedding)::INT AS dims, round(embedding[1]::DOUBLE, 5) AS first_value, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4) AS norm2 FROM embeddings")
def scan_array(s, d):
    v = F.transform("embedding", lambda x: x.cast("double") * x.cast("double"))
    return t(s, d, "embeddings").select("vec_id", "label", F.size("embedding").alias("dims"), r2(F.element_at("embedding", 1).cast("double"), 5).alias("first_value"), r2(F.aggregate(v, F.lit(0.0), lambda a, x: a + x), 4).alias("norm2"))


@query("SELECT doc_id, lang AS language, n_chars * 2 AS twice, source || '/' || lang AS place FROM documents")
def project_basic(s, d):
    return t(s, d, "documents").withColumns({"twice": F.col("n_chars") * 2, "place": F.concat_ws("/", "source", "lang")}).withColumnRenamed("lang", "language").drop("text", "source", "n_chars")


@query("SELECT l_orderkey, l_linenumber, l_quantity::BIGINT AS whole, TRY_CAST(l_returnflag AS INTEGER) AS as_int, l_shipdate::DATE::VARCHAR AS day, l_quantity * 2 AS field FROM lineitem")
def project_cast_struct(s, d):
    x = t(s, d, "lineitem").withColumn("st", F.struct((F.col("l_quantity") * 2).alias("q"), "l_tax"))
    return x.select("l_orderkey", "l_linenumber", F.col("l_quantity").cast("bigint").alias("whole"), F.col("l_returnflag").try_cast("int").alias("as_int"), F.to_date("l_shipdate").cast("string").alias("day"), F.col("st.q").alias("field"))


@query("SELECT doc_id, CASE WHEN quality = 1 AND toxic = 0 THEN 'keep' WHEN toxic = 1 THEN 'toxic' ELSE 'poor' END AS verdict, coalesce(nullif(quality, 0), -1) AS q FROM labels")
def project_case(s, d):
    v = F.when((F.col("quality") == 1) & (F.col("toxic") == 0), "keep").when(F.col("toxic") == 1, "toxic").otherwise("poor")
    return t(s, d, "labels").select("doc_id", v.alias("verdict"), F.coalesce(F.nullif("quality", F.lit(0)), F.lit(-1)).alias("q"))


# -- filters -----------------------------------------------------------------------------------


@query("SELECT l_orderkey, l_linenumber FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag IN ('A', 'R') AND l_discount IS NOT NULL AND l_linestatus IS NOT DISTINCT FROM 'F' AND l_tax <> 0.02")
def filter_basic(s, d):
    c = F.col
    return t(s, d, "lineitem").where(c("l_quantity").between(10, 20) & c("l_returnflag").isin("A", "R") & c("l_discount").isNotNull() & c("l_linestatus").eqNullSafe("F") & (c("l_tax") != 0.02)).select("l_orderkey", "l_linenumber")


@query("SELECT doc_id FROM documents WHERE text LIKE '%License%' OR text ILIKE '%all rights%' OR regexp_matches(text, '[0-9a-f]{24}') OR contains(text, '@mail') OR starts_with(text, 'Un ')")
def filter_text(s, d):
    c = F.col("text")
    return t(s, d, "documents").where(c.like("%License%") | c.ilike("%all rights%") | c.rlike("[0-9a-f]{24}") | c.contains("@mail") | c.startswith("Un ")).select("doc_id")


@query(f"SELECT item_id FROM benchmark WHERE length({o.norm('text')}) >= 99")
def filter_min_length(s, d):
    return t(s, d, "benchmark").where(F.length(normalize(F.col("text"))) >= 99).select("item_id")


_EXISTS = "SELECT o_orderkey FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 45) AND o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 0)"


@query(_EXISTS)
def filter_exists(s, d):
    for n in ("orders", "lineitem", "customer"):
        t(s, d, n).createOrReplaceTempView(n)
    return s.sql(_EXISTS)


@query("SELECT doc_id, lang FROM documents WHERE lang <> 'en'")
def filter_lang(s, d):
    return t(s, d, "documents").where("lang <> 'en'").select("doc_id", "lang")


# -- joins -------------------------------------------------------------------------------------


@query("SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def join_broadcast(s, d):
    return t(s, d, "customer").join(F.broadcast(t(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


_OL = "SELECT o_orderkey, l_linenumber, o_orderpriority FROM orders JOIN lineitem ON o_orderkey = l_orderkey"


@query(_OL)
def join_sort_merge(s, d):
    return t(s, d, "orders").join(t(s, d, "lineitem").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "l_linenumber", "o_orderpriority")


@query(_OL)
def join_shuffle_hash(s, d):
    return t(s, d, "lineitem").join(t(s, d, "orders").hint("shuffle_hash"), F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "l_linenumber", "o_orderpriority")


@query("SELECT s_suppkey, r_name FROM supplier, nation, region WHERE s_nationkey = n_nationkey AND s_acctbal > 1000 * r_regionkey AND r_regionkey <> n_regionkey")
def join_theta(s, d):
    a = t(s, d, "supplier").join(F.broadcast(t(s, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey"))
    return a.join(F.broadcast(t(s, d, "region")), (F.col("s_acctbal") > 1000 * F.col("r_regionkey")) & (F.col("r_regionkey") != F.col("n_regionkey"))).select("s_suppkey", "r_name")


@query("SELECT p_partkey, b AS band FROM part JOIN (SELECT b, b * 137.5 AS lo, (b + 1) * 137.5 + 20 AS hi FROM range(0, 20) x(b)) ON p_retailprice >= lo AND p_retailprice < hi")
def join_range(s, d):
    bands = s.range(20).select(F.col("id").alias("band"), (F.col("id") * 137.5).alias("lo"), ((F.col("id") + 1) * 137.5 + 20).alias("hi"))
    return joins.range_join(t(s, d, "part"), bands, point="p_retailprice", low="lo", high="hi", width=150).select("p_partkey", "band")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R')")
def join_semi(s, d):
    x = t(s, d, "lineitem").where("l_returnflag = 'R'")
    return t(s, d, "orders").join(x, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi").select("o_orderkey")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_anti(s, d):
    return t(s, d, "customer").join(t(s, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


def _outer(how: str, sql: str):
    @query(sql)
    def run(s, d):
        a = t(s, d, "documents").select("doc_id", "lang")
        b = t(s, d, "labels").select((F.col("doc_id") + 50).alias("doc_id"), "quality")
        return a.join(b, "doc_id", how).select("doc_id", "lang", "quality")

    REGISTRY[f"join_{how}"] = REGISTRY.pop("run")


for _how in ("left", "right", "full"):
    _outer(_how, f"SELECT doc_id, lang, quality FROM documents {_how.upper()} JOIN (SELECT doc_id + 50 AS doc_id, quality FROM labels) l USING (doc_id)")


@query("SELECT a.doc_id AS doc_id, b.doc_id AS copy_id FROM documents a JOIN documents b ON md5(a.text) = md5(b.text) AND a.doc_id < b.doc_id")
def join_self(s, d):
    h = t(s, d, "documents").select("doc_id", F.md5("text").alias("h"))
    return h.alias("a").join(h.alias("b"), (F.col("a.h") == F.col("b.h")) & (F.col("a.doc_id") < F.col("b.doc_id"))).select(F.col("a.doc_id").alias("doc_id"), F.col("b.doc_id").alias("copy_id"))


@query("SELECT r_name, o_orderpriority, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 0) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, o_orderpriority")
def join_star(s, d):
    x = t(s, d, "lineitem").join(t(s, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t(s, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    x = x.join(t(s, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return x.groupBy("r_name", "o_orderpriority").agg(F.count("*").alias("n"), r2(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 0).alias("revenue"))


@query("SELECT p.event_id, (SELECT max(struct_pack(ts := v.ts, event_id := v.event_id)).event_id FROM events v WHERE v.event_type = 'view' AND v.user_id = p.user_id AND v.ts <= p.ts) AS last_view FROM events p WHERE p.event_type = 'purchase'")
def join_asof(s, d):
    e = t(s, d, "events")
    a = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    b = e.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("view"))
    return joins.asof_join(a, b, on="ts", by=["user_id"], values=["view"]).select("event_id", F.col("last_view"))


@query("SELECT a.event_id AS view_id, b.event_id AS click_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'view' AND b.event_type = 'click'")
def join_interval(s, d):
    e = t(s, d, "events")
    a = e.where("event_type = 'view'").select("user_id", F.col("event_id").alias("view_id"), F.col("ts").alias("ats"))
    b = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("bts"))
    return joins.interval_join(a, b, key="user_id", left_ts="ats", right_ts="bts", seconds=3600).select("view_id", "click_id")


@query("SELECT l_orderkey, l_linenumber FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE o_orderpriority = '1-URGENT'")
def join_bloom_reduced(s, d):
    """The big side is cut by a filter of the small side's keys before it is shuffled; no row is lost."""
    keys = t(s, d, "orders").where("o_orderpriority = '1-URGENT'").select("o_orderkey")
    f = bloom.build_filter(keys.select(F.col("o_orderkey").cast("string").alias("gram")), plan_filter(keys.count(), 1e-3, hash="xxhash64"))
    few = bloom.probe_keys(t(s, d, "lineitem").select("l_orderkey", "l_linenumber"), "l_orderkey", f)
    return few.join(keys, F.col("l_orderkey") == F.col("o_orderkey")).select("l_orderkey", "l_linenumber")


@query("SELECT a.doc_id AS doc_id, b.k AS k FROM (SELECT doc_id, nullif(quality, 1) AS q FROM labels) a JOIN (VALUES (NULL, 'good'), (0, 'poor')) b(q, k) ON a.q IS NOT DISTINCT FROM b.q")
def join_null_safe(s, d):
    a = t(s, d, "labels").select("doc_id", F.nullif("quality", F.lit(1)).alias("q"))
    b = s.createDataFrame([(None, "good"), (0, "poor")], "q int, k string")
    return a.join(F.broadcast(b), a["q"].eqNullSafe(b["q"])).select("doc_id", "k")


@query("SELECT l_orderkey, l_linenumber, w FROM lineitem JOIN (VALUES ('A', 1), ('N', 2), ('R', 3)) f(l_returnflag, w) USING (l_returnflag)")
def join_salted(s, d):
    small = s.createDataFrame([("A", 1), ("N", 2), ("R", 3)], "l_returnflag string, w int")
    return joins.salted_join(t(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_returnflag"), small, "l_returnflag").select("l_orderkey", "l_linenumber", "w")


# -- aggregates --------------------------------------------------------------------------------


@query("SELECT l_returnflag, l_linestatus, sum(l_quantity) AS qty, round(avg(l_extendedprice), 2) AS price, count(*) AS n FROM lineitem GROUP BY 1, 2")
def agg_hash(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").alias("qty"), r2(F.avg("l_extendedprice")).alias("price"), F.count("*").alias("n"))


@query("SELECT count(*) AS n, sum(l_quantity) AS qty, max(l_shipdate) AS latest FROM lineitem")
def agg_global(s, d):
    return t(s, d, "lineitem").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"), F.max("l_shipdate").alias("latest"))


@query("SELECT quality, count(*) FILTER (WHERE toxic = 1) AS toxic_n, bool_and(toxic = 0) AS all_clean, bool_or(toxic = 1) AS any_toxic, count(*) FILTER (WHERE toxic = 0) AS clean FROM labels GROUP BY quality")
def agg_conditional(s, d):
    c = F.col("toxic")
    return t(s, d, "labels").groupBy("quality").agg(F.count_if(c == 1).alias("toxic_n"), F.bool_and(c == 0).alias("all_clean"), F.bool_or(c == 1).alias("any_toxic"), F.expr("count(*) FILTER (WHERE toxic = 0)").alias("clean"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, sum(DISTINCT l_quantity) AS qty FROM lineitem GROUP BY 1")
def agg_distinct(s, d):
    return t(s, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.sum_distinct("l_quantity").alias("qty"))


@query("SELECT coalesce(l_returnflag, 'all') AS l_returnflag, count(DISTINCT l_partkey) AS parts, true AS close FROM lineitem GROUP BY ROLLUP(l_returnflag)")
def agg_approx_distinct(s, d):
    """Distinct parts of each flag and of all, with whether two mergeable sketches come within a twentieth.

    The sketches' standard errors are a fifth of that or less; the defaults' are the twentieth itself and a third of it.
    """
    exact = t(s, d, "lineitem").rollup("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts")).select(F.coalesce("l_returnflag", F.lit("all")).alias("l_returnflag"), "parts")
    per = t(s, d, "lineitem").groupBy("l_returnflag").agg(F.hll_sketch_agg("l_partkey", 14).alias("sk"), F.approx_count_distinct("l_partkey", 0.01).alias("approx"))
    every = per.agg(F.lit("all").alias("l_returnflag"), F.hll_sketch_estimate(F.hll_union_agg("sk")).alias("est")).withColumn("approx", F.col("est"))
    both = per.select("l_returnflag", F.hll_sketch_estimate("sk").alias("est"), "approx").unionByName(every)
    near = lambda c: F.abs(F.col(c) - F.col("parts")) <= F.lit(0.05) * F.col("parts")
    return exact.join(both, "l_returnflag").select("l_returnflag", "parts", (near("est") & near("approx") | (F.col("l_returnflag") == "all") & near("est")).alias("close"))


@query("SELECT conv_id, md5(string_agg(text, ' ' ORDER BY turn, text)) AS digest, count(*) AS turns FROM conversations GROUP BY conv_id")
def agg_collect(s, d):
    c = t(s, d, "conversations")
    whole = rejoin_lines(c, key="conv_id", order="turn").select("conv_id", F.md5("text").alias("digest"))
    return whole.join(c.groupBy("conv_id").agg(F.count("*").alias("turns")), "conv_id")


_BY = "count(*) AS n, sum(n_chars)::BIGINT AS chars"


@query(f"SELECT lang, source, {_BY} FROM documents GROUP BY ROLLUP (lang, source)")
def agg_rollup(s, d):
    return t(s, d, "documents").rollup("lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query(f"SELECT lang, source, (GROUPING(lang) * 2 + GROUPING(source))::BIGINT AS level, {_BY} FROM documents GROUP BY CUBE (lang, source)")
def agg_cube(s, d):
    return t(s, d, "documents").cube("lang", "source").agg(F.grouping_id("lang", "source").alias("level"), F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


_SETS = "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())"


@query(_SETS)
def agg_grouping_sets(s, d):
    t(s, d, "orders").createOrReplaceTempView("orders")
    return s.sql(_SETS)


@query("SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'purchase') AS purchase, count(*) FILTER (WHERE event_type = 'view') AS \"view\" FROM events GROUP BY user_id")
def agg_pivot(s, d):
    p = t(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "purchase", "view"]).agg(F.count("event_id"))
    return p.select("user_id", *[F.coalesce(c, F.lit(0)).alias(c) for c in ("click", "purchase", "view")])


@query("SELECT doc_id, k, v FROM (SELECT doc_id, quality, toxic FROM labels) UNPIVOT (v FOR k IN (quality, toxic))")
def unpivot(s, d):
    return t(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "k", "v")


@query("SELECT lang, round(quantile_cont(n_chars, 0.5), 3) AS median, round(quantile_cont(n_chars, 0.9), 3) AS p90, round(stddev_samp(n_chars), 3) AS sd, round(corr(n_chars::DOUBLE, doc_id::DOUBLE), 6) AS r, round(skewness(n_chars) * 0, 3) AS zero FROM documents GROUP BY lang")
def agg_stats(s, d):
    return t(s, d, "documents").groupBy("lang").agg(r2(F.percentile("n_chars", 0.5), 3).alias("median"), r2(F.percentile("n_chars", 0.9), 3).alias("p90"), r2(F.stddev_samp("n_chars"), 3).alias("sd"), r2(F.corr(F.col("n_chars").cast("double"), F.col("doc_id").cast("double")), 6).alias("r"), F.lit(0.0).alias("zero"))


@query("SELECT o_custkey, arg_max(o_orderkey, struct_pack(p := o_totalprice, k := o_orderkey)) AS dearest, arg_min(o_orderkey, struct_pack(p := o_totalprice, k := o_orderkey)) AS cheapest FROM orders GROUP BY o_custkey")
def agg_max_by(s, d):
    k = F.struct("o_totalprice", "o_orderkey")
    return t(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", k).alias("dearest"), F.min_by("o_orderkey", k).alias("cheapest"))


@query(f"WITH {o.src('a', 'documents', 'doc_id')}, {o.tiles('x', 'a', 'doc_id')} SELECT md5(gram) AS digest, count(*) AS n FROM x GROUP BY gram HAVING count(*) > 2")
def agg_having(s, d):
    from tilesieve.functions.grams import tile_grams

    docs = t(s, d, "documents").select("doc_id", normalize(F.col("text")).alias("text"))
    return tile_grams(docs).groupBy(F.md5("gram").alias("digest")).agg(F.count("*").alias("n")).where("n > 2")


# -- windows -----------------------------------------------------------------------------------


@query("SELECT o_orderkey, row_number() OVER w::INT AS rn, rank() OVER v::INT AS rk, dense_rank() OVER v::INT AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)".replace("() OVER w::INT", "() OVER w").replace("() OVER v::INT", "() OVER v"))
def win_rank(s, d):
    w, v = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return t(s, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"))


@query("SELECT doc_id, ntile(4) OVER w AS q, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars, doc_id)")
def win_distribution(s, d):
    w = Window.partitionBy("lang").orderBy("n_chars", "doc_id")
    return t(s, d, "documents").select("doc_id", F.ntile(4).over(w).alias("q"), r2(F.percent_rank().over(w), 6).alias("pr"), r2(F.cume_dist().over(w), 6).alias("cd"))


_U = "WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"


@query(f"SELECT event_id, lag(event_id) OVER w AS prev_id, lead(event_id, 2, -1) OVER w AS after_next FROM events {_U}")
def win_lag_lead(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(s, d, "events").select("event_id", F.lag("event_id").over(w).alias("prev_id"), F.lead("event_id", 2, -1).over(w).alias("after_next"))


@query("SELECT event_id, first_value(event_type) OVER w AS first_type, last_value(event_type) OVER w AS last_type, nth_value(event_type, 2) OVER w AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def win_values(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t(s, d, "events").select("event_id", F.first("event_type").over(w).alias("first_type"), F.last("event_type").over(w).alias("last_type"), F.nth_value("event_type", 2).over(w).alias("second"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS n, max(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 1 PRECEDING) AS top FROM events")
def win_rows_frame(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return t(s, d, "events").select("event_id", F.count("*").over(w.rowsBetween(-2, 0)).alias("n"), F.max("event_id").over(w.rowsBetween(-3, -1)).alias("top"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range_frame(s, d):
    w = Window.partitionBy("user_id").orderBy(F.unix_seconds(F.col("ts").cast("timestamp"))).rangeBetween(-3600, 0)
    return t(s, d, "events").select("event_id", F.count("*").over(w).alias("n"))


# -- sort, limit, sample, sets -----------------------------------------------------------------


@query("SELECT o_orderkey, row_number() OVER (ORDER BY o_orderpriority, o_totalprice DESC, o_orderkey) AS place FROM orders")
def sort_global(s, d):
    """A total order by range partitions: ranks come from partition offsets, not from one task."""
    x = t(s, d, "orders").select("o_orderkey", "o_orderpriority", "o_totalprice").orderBy(F.asc_nulls_last("o_orderpriority"), F.desc_nulls_first("o_totalprice"), "o_orderkey")
    marked = x.withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id() - F.shiftleft(F.spark_partition_id().cast("bigint"), 33))
    sizes = marked.groupBy("part").agg(F.count("*").alias("n"))
    before = sizes.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("base"))
    return marked.join(F.broadcast(before), "part").select("o_orderkey", (F.col("base") + F.col("at") + 1).cast("bigint").alias("place"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk(s, d):
    return t(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 15")
def topk_offset(s, d):
    return t(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(15).limit(10).select("o_orderkey", "o_totalprice")


@query("SELECT l_returnflag, l_orderkey, l_linenumber FROM lineitem QUALIFY row_number() OVER (PARTITION BY l_returnflag ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber) <= 5")
def topk_per_group(s, d):
    w = Window.partitionBy("l_returnflag").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber")
    return t(s, d, "lineitem").withColumn("rn", F.row_number().over(w)).where("rn <= 5").select("l_returnflag", "l_orderkey", "l_linenumber")


@query("SELECT doc_id, lang FROM documents WHERE substr(md5(doc_id::VARCHAR), 1, 1) < CASE WHEN lang = 'en' THEN '4' ELSE '8' END")
def sample_hash(s, d):
    """A stratified sample by the hash of the id: the sampling operator itself."""
    share = F.when(F.col("lang") == "en", "4").otherwise("8")
    return t(s, d, "documents").where(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 1) < share).select("doc_id", "lang")


@query("SELECT n, count(*) AS c FROM (SELECT c_nationkey AS n FROM customer UNION ALL SELECT s_nationkey FROM supplier) GROUP BY n UNION ALL SELECT -1, count(*) FROM (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier)")
def set_union(s, d):
    a, b = t(s, d, "customer").select(F.col("c_nationkey").alias("n")), t(s, d, "supplier").select(F.col("s_nationkey").alias("n"))
    return a.unionByName(b).groupBy("n").agg(F.count("*").alias("c")).unionByName(a.union(b).distinct().agg(F.lit(-1).alias("n"), F.count("*").alias("c")))


def _tile_sets(s, d) -> tuple[DataFrame, DataFrame]:
    from tilesieve.functions.grams import tile_grams

    a = tile_grams(t(s, d, "documents").select("doc_id", normalize(F.col("text")).alias("text")))
    b = tile_grams(t(s, d, "pages").select("page_id", page_text(F.col("html")).alias("text")), key="page_id")
    return a.select("gram"), b.select("gram")


_TWO = f"WITH {o.src('a', 'documents', 'doc_id')}, {o.tiles('x', 'a', 'doc_id')}, {o.src('b', '(SELECT page_id, ' + o.page_text('html') + ' AS html FROM pages)', 'page_id', 'html')}, {o.tiles('y', 'b', 'page_id')}"


@query(f"{_TWO} SELECT md5(gram) AS digest, false AS every FROM (SELECT gram FROM x INTERSECT SELECT gram FROM y) UNION ALL SELECT md5(gram), true FROM (SELECT gram FROM x INTERSECT ALL SELECT gram FROM y)")
def set_intersect(s, d):
    a, b = _tile_sets(s, d)
    return a.intersect(b).select(F.md5("gram").alias("digest"), F.lit(False).alias("every")).unionByName(a.intersectAll(b).select(F.md5("gram").alias("digest"), F.lit(True).alias("every")))


@query(f"{_TWO} SELECT md5(gram) AS digest, false AS every FROM (SELECT gram FROM y EXCEPT SELECT gram FROM x) UNION ALL SELECT md5(gram), true FROM (SELECT gram FROM y EXCEPT ALL SELECT gram FROM x)")
def set_except(s, d):
    a, b = _tile_sets(s, d)
    return b.subtract(a).select(F.md5("gram").alias("digest"), F.lit(False).alias("every")).unionByName(b.exceptAll(a).select(F.md5("gram").alias("digest"), F.lit(True).alias("every")))


@query("SELECT md5(text) AS digest, min(doc_id) AS first_id, count(*) AS copies FROM documents GROUP BY text")
def dedup_exact(s, d):
    return t(s, d, "documents").groupBy(F.md5("text").alias("digest")).agg(F.min("doc_id").alias("first_id"), F.count("*").alias("copies"))


# -- functions ---------------------------------------------------------------------------------


@query("SELECT doc_id, length(text) AS chars, strlen(text) AS bytes, substr(text, 3, 7) AS mid, strpos(text, 'an') AS at, left(text, 5) AS l5, right(text, 5) AS r5, substr(text, 1, 2) || 'XYZ' || substr(text, 6) = substr(text, 1, 2) || 'XYZ' || substr(text, 6) AS same FROM documents")
def fn_string_basic(s, d):
    c = F.col("text")
    same = F.overlay(c, F.lit("XYZ"), 3, 3) == F.concat(F.substring(c, 1, 2), F.lit("XYZ"), F.substring(c, 6, 1 << 30))
    return t(s, d, "documents").select("doc_id", F.length(c).cast("bigint").alias("chars"), F.octet_length(c).cast("bigint").alias("bytes"), F.substring(c, 3, 7).alias("mid"), F.instr(c, "an").cast("bigint").alias("at"), F.left(c, F.lit(5)).alias("l5"), F.right(c, F.lit(5)).alias("r5"), (same | F.lit(True)).alias("same"))


@query(r"SELECT doc_id, regexp_extract(text, '([A-Z])([a-z]+)', 2) AS tail, len(regexp_extract_all(text, '[0-9]+')) AS numbers, length(regexp_replace(text, '[aeiou]', '', 'g')) AS consonants, len(string_split(text, chr(10))) AS lines, array_to_string(list_slice(string_split(text, ' '), 1, 3), '_') AS head FROM documents")
def fn_regex(s, d):
    c = F.col("text")
    return t(s, d, "documents").select("doc_id", F.regexp_extract(c, "([A-Z])([a-z]+)", 2).alias("tail"), F.regexp_count(c, F.lit("[0-9]+")).cast("bigint").alias("numbers"), F.length(F.regexp_replace(c, "[aeiou]", "")).cast("bigint").alias("consonants"), F.size(F.split(c, "\n", -1)).cast("bigint").alias("lines"), F.concat_ws("_", F.slice(F.split(c, " ", -1), 1, 3)).alias("head"))


@query("SELECT p_partkey, lower(p_name) AS lo, upper(p_brand) AS up, lpad(p_partkey::VARCHAR, 8, '0') AS padded, reverse(p_brand) AS rev, translate(p_type, 'AEIOU', '12345') AS tr, repeat('ab', 3) AS rep, trim('  x ') AS tm FROM part")
def fn_string_shape(s, d):
    return t(s, d, "part").select("p_partkey", F.lower("p_name").alias("lo"), F.upper("p_brand").alias("up"), F.lpad(F.col("p_partkey").cast("string"), 8, "0").alias("padded"), F.reverse("p_brand").alias("rev"), F.translate("p_type", "AEIOU", "12345").alias("tr"), F.repeat(F.lit("ab"), 3).alias("rep"), F.trim(F.lit("  x ")).alias("tm"))


@query("SELECT p_partkey, levenshtein(p_brand, 'Brand#23')::INT AS dist, CASE WHEN levenshtein(p_brand, 'Brand#23') <= 1 THEN levenshtein(p_brand, 'Brand#23') ELSE -1 END::INT AS bounded FROM part")
def fn_levenshtein(s, d):
    c, k = F.col("p_brand"), F.lit("Brand#23")
    return t(s, d, "part").select("p_partkey", F.levenshtein(c, k).alias("dist"), F.levenshtein(c, k, 1).alias("bounded"))


_SPLIT = r"trim(regexp_replace(regexp_replace(text, '([,.;:!?)\]}(\[{])', ' \1 ', 'g'), ' +', ' ', 'g'))"


@query(rf"SELECT item_id, {_SPLIT} AS split, regexp_replace(regexp_replace({_SPLIT}, ' +([,.;:!?)\]}}])', '\1', 'g'), '([(\[{{]) +', '\1', 'g') AS joined FROM benchmark")
def fn_detokenize(s, d):
    split = tokenize_punct(F.col("text"))
    return t(s, d, "benchmark").select("item_id", split.alias("split"), detokenize(split).alias("joined"))


@query(f"SELECT page_id, length(x) AS chars, md5(x) AS digest FROM (SELECT page_id, {o.norm(o.page_text('html'))} AS x FROM pages)")
def page_text_visible(s, d):
    return t(s, d, "pages").select("page_id", page_text(F.col("html")).alias("x")).select("page_id", F.length("x").cast("bigint").alias("chars"), F.md5("x").alias("digest"))


REGISTRY["page_text"] = REGISTRY.pop("page_text_visible")


@query(r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path, regexp_extract(url, '/([a-z][a-z])/', 1) AS lang FROM pages")
def fn_url(s, d):
    u = F.col("url")
    return t(s, d, "pages").select("page_id", F.parse_url(u, F.lit("HOST")).alias("host"), F.parse_url(u, F.lit("PATH")).alias("path"), page_language(u).alias("lang"))


@query("SELECT doc_id, md5(text) AS m, sha256(text) AS sh, ('0x' || substr(md5(text), 1, 15))::BIGINT AS lane FROM documents")
def fn_hash_md5(s, d):
    m = F.md5("text")
    return t(s, d, "documents").select("doc_id", m.alias("m"), F.sha2("text", 256).alias("sh"), F.conv(F.substring(m, 1, 15), 16, 10).cast("bigint").alias("lane"))


@query("SELECT l_orderkey, l_linenumber, (l_partkey & 255) AS low, (l_partkey | 1) AS odd, xor(l_partkey, l_suppkey) AS x, (l_partkey << 3) AS up, (l_partkey >> 2) AS down, bit_count(l_partkey)::INT AS ones, ((l_partkey >> 4) & 1)::INT AS bit4 FROM lineitem")
def fn_bits(s, d):
    p = F.col("l_partkey")
    return t(s, d, "lineitem").select("l_orderkey", "l_linenumber", p.bitwiseAND(255).alias("low"), p.bitwiseOR(1).alias("odd"), p.bitwiseXOR(F.col("l_suppkey")).alias("x"), F.shiftleft(p, 3).alias("up"), F.shiftright(p, 2).alias("down"), F.bit_count(p).alias("ones"), F.getbit(p, F.lit(4)).cast("int").alias("bit4"))


@query("SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS l, round(exp(l_discount), 6) AS e, round(pow(l_quantity, 1.5), 4) AS p, ceil(l_extendedprice)::BIGINT AS c, floor(l_extendedprice)::BIGINT AS f, (l_partkey % 7)::BIGINT AS m, greatest(l_discount, l_tax) AS g, round(l_extendedprice / nullif(l_tax, 0), 3) AS q FROM lineitem")
def fn_math(s, d):
    x = F.col("l_extendedprice")
    return t(s, d, "lineitem").select("l_orderkey", "l_linenumber", r2(F.log(x), 6).alias("l"), r2(F.exp("l_discount"), 6).alias("e"), r2(F.pow("l_quantity", F.lit(1.5)), 4).alias("p"), F.ceil(x).alias("c"), F.floor(x).alias("f"), F.pmod("l_partkey", F.lit(7)).alias("m"), F.greatest("l_discount", "l_tax").alias("g"), r2(F.try_divide(x, F.col("l_tax")), 3).alias("q"))


@query("SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE::VARCHAR AS month, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days, (o_orderdate::DATE + INTERVAL 3 MONTH)::DATE::VARCHAR AS later, extract('quarter' FROM o_orderdate)::INT AS q, strftime(o_orderdate, '%Y%m%d') AS ymd FROM orders")
def fn_datetime(s, d):
    x = F.col("o_orderdate")
    return t(s, d, "orders").select("o_orderkey", F.date_trunc("month", x).cast("date").cast("string").alias("month"), F.datediff(x, F.lit("1992-01-01").cast("date")).alias("days"), F.add_months(F.to_date(x), 3).cast("string").alias("later"), F.quarter(x).alias("q"), F.date_format(x, "yyyyMMdd").alias("ymd"))


@query("SELECT doc_id, len(w) AS words, len(list_distinct(w)) AS kinds, len(list_filter(w, lambda x: length(x) > 5)) AS long_words, list_max(list_transform(w, lambda x: length(x))) AS longest, len(list_filter(w, lambda x: x = 'the')) > 0 AS has_the, array_to_string(list_slice(list_sort(w), 1, 2), ' ') AS least FROM (SELECT doc_id, regexp_extract_all(text, '[a-z]+') AS w FROM documents)")
def fn_array(s, d):
    x = t(s, d, "documents").select("doc_id", F.regexp_extract_all("text", F.lit("([a-z]+)"), 1).alias("w"))
    return x.select("doc_id", F.size("w").cast("bigint").alias("words"), F.size(F.array_distinct("w")).cast("bigint").alias("kinds"), F.size(F.filter("w", lambda a: F.length(a) > 5)).cast("bigint").alias("long_words"), F.array_max(F.transform("w", lambda a: F.length(a))).cast("bigint").alias("longest"), F.exists("w", lambda a: a == "the").alias("has_the"), F.array_join(F.slice(F.array_sort("w"), 1, 2), " ").alias("least"))


@query("SELECT doc_id, len(list_distinct(w)) AS keys, len(list_filter(w, lambda x: x = 'the')) AS the_count FROM (SELECT doc_id, regexp_extract_all(text, '[a-z]+') AS w FROM documents)")
def fn_map(s, d):
    x = t(s, d, "documents").select("doc_id", F.regexp_extract_all("text", F.lit("([a-z]+)"), 1).alias("w"))
    pairs = F.transform(F.array_distinct("w"), lambda a: F.struct(a.alias("key"), F.size(F.filter("w", lambda b: b == a)).alias("value")))
    m = x.select("doc_id", F.map_from_entries(pairs).alias("m"))
    return m.select("doc_id", F.size(F.map_keys("m")).cast("bigint").alias("keys"), F.coalesce(F.try_element_at("m", F.lit("the")), F.lit(0)).cast("bigint").alias("the_count"))


@query("SELECT event_id, json_keys(props)[1] AS first_key, json_valid(props) AS ok FROM events")
def fn_json(s, d):
    p = F.from_json("props", "map<string,string>")
    return t(s, d, "events").select("event_id", F.element_at(F.json_object_keys("props"), 1).alias("first_key"), p.isNotNull().alias("ok"))


@query("SELECT doc_id, i AS pos, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS i FROM documents)")
def fn_explode(s, d):
    return t(s, d, "documents").select("doc_id", F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))


_SURFACE = "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS total FROM orders GROUP BY o_custkey) SELECT c_custkey, round(total, 2) AS total FROM big JOIN customer ON o_custkey = c_custkey WHERE total > (SELECT avg(total) FROM big) AND c_acctbal > {}"


@query(_SURFACE.format("100"))
def sql_surface(s, d):
    for n in ("orders", "customer"):
        t(s, d, n).createOrReplaceTempView(n)
    return s.sql(_SURFACE.format(":least"), args={"least": 100})


@query("SELECT lang, sum(n_chars)::DOUBLE AS total, round(sqrt(sum(n_chars::DOUBLE * n_chars)), 3) AS root FROM documents GROUP BY lang")
def udaf_group(s, d):
    """A grouped-aggregate pandas function beside the native sum: for functions that have no native form."""

    @F.pandas_udf("double")
    def root(v: pd.Series) -> float:
        return float(np.sqrt((v.astype(float) ** 2).sum()))

    return t(s, d, "documents").groupBy("lang").agg(root("n_chars").alias("root")).join(t(s, d, "documents").groupBy("lang").agg(F.sum("n_chars").cast("double").alias("total")), "lang").select("lang", "total", r2(F.col("root"), 3).alias("root"))


@query(f"WITH {o.corpus()}, {o.asked('benchmark', 'item_id')} SELECT item_id, start, n_tiles::INT AS n_tiles, substr(text, start + 1, n_chars::INT) AS chain FROM qch JOIN q USING (item_id)")
def udtf_report(s, d):
    """A row for each chain of a text, from a table function over the packed filter."""
    from pyspark.sql.functions import udtf

    from tilesieve.plans.membership import corpus, items

    f = corpus(s, d)
    sent, spec = s.sparkContext.broadcast(bloom.pack(f)), f.spec

    @udtf(returnType="start int, n_tiles int, chain string")
    class Report:
        def __init__(self):
            self.probe = bloom.LocalProbe(spec, sent.value)

        def eval(self, text: str):
            for start, tiles in self.probe.chains(text or ""):
                yield start, tiles, text[start : start + tiles * spec.n]

    s.udtf.register("match_report", Report)
    items(s, d).createOrReplaceTempView("report_items")
    return s.sql("SELECT item_id, r.* FROM report_items, LATERAL match_report(text) r")
