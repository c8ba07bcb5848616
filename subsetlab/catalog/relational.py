"""Operators around the methods, each with its SQL."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import levels as L
from ..operators import relational as X
from ..operators.entropy import sample_entropy
from ..operators.pairs import similar_pairs
from ..operators.sampling import hash_order
from ..operators.select import top_n, top_q_per_group
from ..sources.tables import read, register_views, stage, table, work_dir, write
from . import sqlparts as P
from .inputs import docs, e_all
from .registry import Registry

R = Registry()
T = table


@R.add("op_scan_project", "SELECT doc_id, CAST(n_chars AS VARCHAR) AS n_text, n_chars / 1000.0::DOUBLE AS kilo FROM documents")
def _(s, d):
    return T(s, d, "documents").select("doc_id", F.col("n_chars").cast("string").alias("n_text"), (F.col("n_chars") / F.lit(1000.0)).alias("kilo"))


@R.add("op_filter_predicates", "SELECT p_partkey, p_brand FROM part WHERE p_size BETWEEN 5 AND 30 AND (p_type IN (SELECT p_type FROM part ORDER BY p_type LIMIT 1) OR p_name LIKE '%a%') AND NOT (p_brand IS NOT DISTINCT FROM 'Brand#11')")
def _(s, d):
    part = T(s, d, "part")
    first = part.agg(F.min("p_type")).first()[0]
    return part.filter(F.col("p_size").between(5, 30) & (F.col("p_type").isin(first) | F.col("p_name").like("%a%")) & ~F.col("p_brand").eqNullSafe("Brand#11")).select("p_partkey", "p_brand")


@R.add("op_join_broadcast", "SELECT s_suppkey, n_name, r_name FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def _(s, d):
    n = T(s, d, "nation").join(F.broadcast(T(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 and 5 rows
    return T(s, d, "supplier").join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name", "r_name")


@R.add("op_join_shuffle_hash", "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey")
def _(s, d):
    return T(s, d, "orders").join(T(s, d, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment")


@R.add("op_join_sort_merge", "SELECT o_orderkey, count(*) AS lines, round(sum(l_extendedprice), 2) AS price FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def _(s, d):
    j = T(s, d, "orders").join(T(s, d, "lineitem").hint("merge"), F.col("o_orderkey") == F.col("l_orderkey"))
    return j.groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("lines"), F.round(F.sum("l_extendedprice"), 2).alias("price"))


for _how, _sql in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):

    @R.add(f"op_join_{_how}", f"SELECT coalesce(a.doc_id, b.doc_id) AS doc_id, quality, n_chars FROM (SELECT doc_id, n_chars FROM documents WHERE lang <> 'fr') a {_sql} JOIN labels b ON a.doc_id = b.doc_id")
    def _(s, d, how=_how):
        a, b = T(s, d, "documents").filter("lang <> 'fr'").select("doc_id", "n_chars"), T(s, d, "labels")
        return a.join(b, "doc_id", how).select("doc_id", "quality", "n_chars")


@R.add("op_join_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")
def _(s, d):
    return T(s, d, "documents").join(T(s, d, "labels").filter("quality = 1"), "doc_id", "left_semi").select("doc_id", "lang")


@R.add("op_join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def _(s, d):
    return T(s, d, "documents").join(T(s, d, "labels"), "doc_id", "left_anti").select("doc_id")


@R.add("op_join_cross", "SELECT n_name, r_name FROM nation CROSS JOIN region")
def _(s, d):
    return T(s, d, "nation").crossJoin(T(s, d, "region")).select("n_name", "r_name")


@R.add("op_join_theta", "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_partkey < b.p_partkey AND abs(a.p_size - b.p_size) <= 1")
def _(s, d):
    p = T(s, d, "part").select("p_partkey", "p_brand", "p_type", "p_size")
    # The band is part of the key: a row meets the sizes one below, equal and one above, not its whole brand and type.
    a, b = p.alias("a"), p.withColumn("near", F.explode(F.array(*[F.col("p_size") + k for k in (-1, 0, 1)]))).alias("b")
    on = (F.col("a.p_brand") == F.col("b.p_brand")) & (F.col("a.p_type") == F.col("b.p_type")) & (F.col("a.p_size") == F.col("b.near")) & (F.col("a.p_partkey") < F.col("b.p_partkey"))
    return a.join(b, on).select(F.col("a.p_partkey").alias("a"), F.col("b.p_partkey").alias("b"))


_BANDS = "b AS (SELECT * FROM (VALUES ('low', 0.0, 2.8), ('mid', 2.8, 2.95), ('high', 2.95, 9.0)) v(band, lo, hi))"


@R.add("op_join_range", P.with_(P.DOC_H, _BANDS, select="SELECT id AS sample_id, band FROM dh JOIN b ON round(h, 9) >= lo AND round(h, 9) < hi"))
def _(s, d):
    bands = s.createDataFrame([("low", 0.0, 2.8), ("mid", 2.8, 2.95), ("high", 2.95, 9.0)], "band string, lo double, hi double")
    return X.range_join(sample_entropy(docs(s, d)).withColumn("h", F.round("entropy", 9)), "h", bands, "lo", "hi").select("sample_id", "band")


@R.add("op_join_asof", "SELECT p.event_id, max(c.value) AS value_asof FROM (SELECT * FROM events WHERE event_type = 'purchase') p LEFT JOIN (SELECT user_id, ts, value FROM (SELECT *, rank() OVER (PARTITION BY user_id, ts ORDER BY value DESC) AS rk FROM events WHERE event_type = 'click') WHERE rk = 1) c ON c.user_id = p.user_id AND c.ts = (SELECT max(ts) FROM events x WHERE x.event_type = 'click' AND x.user_id = p.user_id AND x.ts <= p.ts) GROUP BY 1")
def _(s, d):
    e = T(s, d, "events")
    clicks = e.filter("event_type = 'click'").select("user_id", "ts", "value")
    return X.asof_join(e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts"), clicks, "user_id", "ts", "value").select("event_id", "value_asof")


@R.add("op_join_interval", "SELECT a.event_id, b.event_id AS event_id_r FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _(s, d):
    e = T(s, d, "events").select("event_id", "user_id", "ts")
    return X.interval_join(e, e, "user_id", "ts", 3600).select("event_id", "event_id_r")


@R.add("op_join_lateral", "SELECT n_name, s_suppkey FROM nation, LATERAL (SELECT s_suppkey FROM supplier WHERE s_nationkey = n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 3) t")
def _(s, d):
    register_views(s, d, ["nation", "supplier"])
    return s.sql("SELECT n_name, s_suppkey FROM nation, LATERAL (SELECT s_suppkey FROM supplier WHERE s_nationkey = n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 3) t")


@R.add("op_agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS sum_qty, round(avg(l_extendedprice), 4) AS avg_price, min(l_discount) AS min_disc, max(l_tax) AS max_tax FROM lineitem GROUP BY 1, 2")
def _(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("l_quantity"), 2).alias("sum_qty"), F.round(F.avg("l_extendedprice"), 4).alias("avg_price"), F.min("l_discount").alias("min_disc"), F.max("l_tax").alias("max_tax"))


@R.add("op_agg_decimal", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(12,2))) AS DOUBLE) AS total FROM lineitem GROUP BY 1")
def _(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(12,2)")).cast("double").alias("total"))


@R.add("op_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def _(s, d):
    return T(s, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@R.add("op_agg_approx_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, TRUE AS approx, TRUE AS hll, TRUE AS theta FROM events GROUP BY 1")
def _(s, d):
    """Three sketches, each within a twelfth of the exact number."""
    e = T(s, d, "events").groupBy("event_type")
    out = e.agg(F.count_distinct("user_id").alias("users"), F.approx_count_distinct("user_id").alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id")).alias("hll"), F.theta_sketch_estimate(F.theta_sketch_agg("user_id")).alias("theta"))
    return out.select("event_type", "users", *[(F.abs(F.col(c) - F.col("users")) * 12 <= F.col("users")).alias(c) for c in ("approx", "hll", "theta")])


@R.add("op_agg_percentile", P.with_(P.DOC_H, select="SELECT round(quantile_cont(h, 0.25), 6) AS q1, round(quantile_cont(h, 0.5), 6) AS q2, round(quantile_cont(h, 0.75), 6) AS q3 FROM dh"))
def _(s, d):
    h = sample_entropy(docs(s, d))
    return h.agg(*[F.round(F.percentile("entropy", q), 6).alias(f"q{i}") for i, q in enumerate((0.25, 0.5, 0.75), 1)])


@R.add("op_agg_approx_percentile", P.with_(P.DOC_H, select="SELECT count(*) AS n, TRUE AS q1, TRUE AS q2, TRUE AS q3, TRUE AS kll FROM dh"))
def _(s, d):
    """Sketched quantiles whose ranks are right to within a fiftieth of the rows."""
    h = stage(s, sample_entropy(docs(s, d)), "h")
    found = h.agg(F.approx_percentile("entropy", [0.25, 0.5, 0.75], 1000).alias("q"), F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("entropy"), F.lit(0.5)).alias("kll")).first()
    rank = lambda v, q: F.abs(F.count_if(F.col("entropy") <= v) / F.count(F.lit(1)) - q) <= 0.02
    return h.agg(F.count(F.lit(1)).alias("n"), *[rank(v, q).alias(f"q{i}") for i, (v, q) in enumerate(zip(found["q"], (0.25, 0.5, 0.75), strict=True), 1)], rank(found["kll"], 0.5).alias("kll"))


for _kind, _clause in (("grouping_sets", "GROUPING SETS ((lang, source), (lang), ())"), ("cube", "CUBE (lang, source)"), ("rollup", "ROLLUP (lang, source)")):

    @R.add(f"op_agg_{_kind}", f"SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY {_clause}")
    def _(s, d, kind=_kind, clause=_clause):
        df, agg = T(s, d, "documents"), (F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))
        if kind == "grouping_sets":
            return df.groupingSets([["lang", "source"], ["lang"], []], "lang", "source").agg(*agg)
        return getattr(df, kind)("lang", "source").agg(*agg)


@R.add("op_agg_pivot", "SELECT lang, CAST(count(*) FILTER (quality = 0) AS BIGINT) AS q0, CAST(count(*) FILTER (quality = 1) AS BIGINT) AS q1 FROM documents JOIN labels USING (doc_id) GROUP BY 1")
def _(s, d):
    j = T(s, d, "documents").join(T(s, d, "labels"), "doc_id")
    p = j.groupBy("lang").pivot("quality", [0, 1]).count()
    return p.select("lang", F.coalesce("0", F.lit(0)).alias("q0"), F.coalesce("1", F.lit(0)).alias("q1"))


@R.add("op_agg_filter_having", "SELECT source, count(*) AS n, CAST(count(*) FILTER (n_chars > 2000) AS BIGINT) AS long FROM documents GROUP BY 1 HAVING count(*) > 40")
def _(s, d):
    return T(s, d, "documents").groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("n_chars") > 2000).alias("long")).filter("n > 40")


@R.add("op_agg_stats", "SELECT round(var_pop(l_extendedprice) / 1e6, 4) AS v, round(stddev_samp(l_quantity), 6) AS sd, round(corr(l_quantity, l_extendedprice), 6) AS r, round(covar_pop(l_discount, l_tax), 8) AS c FROM lineitem")
def _(s, d):
    return T(s, d, "lineitem").agg(F.round(F.var_pop("l_extendedprice") / 1e6, 4).alias("v"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("r"), F.round(F.covar_pop("l_discount", "l_tax"), 8).alias("c"))


@R.add("op_agg_max_by", "SELECT o_custkey, arg_max(o_orderkey, {'p': o_totalprice, 'k': o_orderkey}) AS best, arg_min(o_orderkey, {'p': o_totalprice, 'k': o_orderkey}) AS least FROM orders GROUP BY 1")
def _(s, d):
    by = F.struct("o_totalprice", "o_orderkey")
    return T(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", by).alias("best"), F.min_by("o_orderkey", by).alias("least"))


@R.add("op_agg_collect", "SELECT lang, list_sort(list(DISTINCT source)) AS sources FROM documents GROUP BY 1")
def _(s, d):
    return T(s, d, "documents").groupBy("lang").agg(F.array_sort(F.collect_set("source")).alias("sources"))


@R.add("op_agg_histogram")
def _(s, d):
    return T(s, d, "documents").groupBy("lang").agg(F.histogram_numeric("n_chars", F.lit(8)).alias("h"))


_OW = "OVER (PARTITION BY o_custkey ORDER BY o_orderstatus, o_orderkey)"
_OT = "OVER (PARTITION BY o_custkey ORDER BY o_orderstatus)"
for _fn, _sql, _tie in (("row_number", "row_number()", False), ("rank", "rank()", True), ("dense_rank", "dense_rank()", True), ("percent_rank", "round(percent_rank() {w}, 6)", True), ("cume_dist", "round(cume_dist() {w}, 6)", True), ("ntile", "ntile(3)", False)):
    _w = _OT if _tie else _OW

    @R.add(f"op_win_{_fn}", f"SELECT o_orderkey, {_sql.format(w=_w) if '{w}' in _sql else _sql + ' ' + _w} AS r FROM orders")
    def _(s, d, fn=_fn, tie=_tie):
        w = W.partitionBy("o_custkey").orderBy(*(["o_orderstatus"] if tie else ["o_orderstatus", "o_orderkey"]))
        f = (F.ntile(3) if fn == "ntile" else getattr(F, fn)()).over(w)
        return T(s, d, "orders").select("o_orderkey", (F.round(f, 6) if fn in ("percent_rank", "cume_dist") else f).alias("r"))


_EW = "OVER (PARTITION BY user_id ORDER BY ts, event_id {f})"


@R.add("op_win_lag_lead", f"SELECT event_id, lag(value) {_EW.format(f='')} AS before, lead(value, 2, -1.0) {_EW.format(f='')} AS after FROM events")
def _(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return T(s, d, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value", 2, -1.0).over(w).alias("after"))


_ALL = "ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING"


@R.add("op_win_first_last_nth", f"SELECT event_id, first_value(value) {_EW.format(f=_ALL)} AS a, last_value(value) {_EW.format(f=_ALL)} AS z, nth_value(value, 2) {_EW.format(f=_ALL)} AS b FROM events")
def _(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return T(s, d, "events").select("event_id", F.first("value").over(w).alias("a"), F.last("value").over(w).alias("z"), F.nth_value("value", 2).over(w).alias("b"))


@R.add("op_win_running_sum", f"SELECT event_id, round(sum(value) {_EW.format(f='ROWS UNBOUNDED PRECEDING')}, 4) AS total FROM events")
def _(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    return T(s, d, "events").select("event_id", F.round(F.sum("value").over(w), 4).alias("total"))


@R.add("op_win_rows_frame", f"SELECT event_id, round(avg(value) {_EW.format(f='ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING')}, 6) AS mean FROM events")
def _(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-1, 1)
    return T(s, d, "events").select("event_id", F.round(F.avg("value").over(w), 6).alias("mean"))


@R.add("op_win_range_interval", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM events")
def _(s, d):
    w = W.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)
    return T(s, d, "events").select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@R.add("op_sessionize", "SELECT event_id, CAST(1 + sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) > INTERVAL 6 HOUR THEN 1 ELSE 0 END AS new FROM events)")
def _(s, d):
    return X.sessionize(T(s, d, "events").select("event_id", "user_id", "ts"), "user_id", "ts", 21_600).select("event_id", F.col("session").cast("long").alias("session"))


@R.add("op_sort_nulls", "SELECT CAST(row_number() OVER (ORDER BY q DESC NULLS LAST, p_partkey) AS INTEGER) AS place, p_partkey FROM (SELECT p_partkey, CASE WHEN p_size > 10 THEN p_retailprice END AS q FROM part)")
def _(s, d):
    q = F.when(F.col("p_size") > 10, F.col("p_retailprice"))
    return T(s, d, "part").withColumn("q", q).select(F.row_number().over(W.orderBy(F.col("q").desc_nulls_last(), "p_partkey")).alias("place"), "p_partkey")


@R.add("op_limit_offset", "SELECT p_partkey FROM part ORDER BY p_retailprice DESC, p_partkey LIMIT 20 OFFSET 10")
def _(s, d):
    return T(s, d, "part").orderBy(F.col("p_retailprice").desc(), "p_partkey").offset(10).limit(20).select("p_partkey")


@R.add("op_topk_global", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100")
def _(s, d):
    return top_n(T(s, d, "orders").select("o_orderkey", "o_totalprice"), 100, "o_totalprice", "o_orderkey")


@R.add("op_topk_group", "SELECT o_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
def _(s, d):
    return top_q_per_group(T(s, d, "orders"), "o_custkey", 2, "o_totalprice", "o_orderkey").select("o_custkey", "o_orderkey")


_SETS = {"union": "UNION", "union_all": "UNION ALL", "intersect": "INTERSECT", "intersect_all": "INTERSECT ALL", "except": "EXCEPT", "except_all": "EXCEPT ALL"}
for _name, _sql in _SETS.items():

    @R.add(f"op_set_{_name}", f"SELECT lang, source FROM documents WHERE n_chars < 1500 {_sql} SELECT lang, source FROM documents WHERE n_chars > 1200 AND lang <> 'es'")
    def _(s, d, name=_name):
        df = T(s, d, "documents")
        a, b = df.filter("n_chars < 1500").select("lang", "source"), df.filter("n_chars > 1200 AND lang <> 'es'").select("lang", "source")
        return {"union": lambda: a.union(b).distinct(), "union_all": lambda: a.unionByName(b), "intersect": lambda: a.intersect(b), "intersect_all": lambda: a.intersectAll(b), "except": lambda: a.subtract(b), "except_all": lambda: a.exceptAll(b)}[name]()


@R.add("op_str_functions", r"SELECT doc_id, length(text) AS n, lower(substr(text, 1, 12)) AS head, regexp_extract(text, '([a-z]+)', 1) AS word, len(string_split(text, ' ')) AS parts, replace(substr(text, 1, 20), 'e', '_') AS swapped, md5(text) AS digest, levenshtein(lang, 'eng') AS lev FROM documents")
def _(s, d):
    t = F.col("text")
    return T(s, d, "documents").select("doc_id", F.length(t).alias("n"), F.lower(F.substring(t, 1, 12)).alias("head"), F.regexp_extract(t, "([a-z]+)", 1).alias("word"), F.size(F.split(t, " ", -1)).alias("parts"), F.replace(F.substring(t, 1, 20), F.lit("e"), F.lit("_")).alias("swapped"), F.md5(t).alias("digest"), F.levenshtein("lang", F.lit("eng")).alias("lev"))


@R.add("op_url_functions", r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path, regexp_replace(url, '[?#].*$', '') AS bare FROM pages")
def _(s, d):
    u = F.col("url")
    return T(s, d, "pages").select("page_id", F.regexp_extract(u, "^[a-z]+://([^/?#]+)", 1).alias("host"), F.regexp_extract(u, "^[a-z]+://[^/?#]+([^?#]*)", 1).alias("path"), F.regexp_replace(u, "[?#].*$", "").alias("bare"))


@R.add("op_date_functions", "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS first, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days FROM orders")
def _(s, d):
    o = F.col("o_orderdate")
    return T(s, d, "orders").select("o_orderkey", F.year(o).alias("y"), F.month(o).alias("m"), F.to_date(F.date_trunc("month", o)).alias("first"), F.date_diff(F.to_date(o), F.lit("1992-01-01").cast("date")).alias("days"))


@R.add("op_math_functions", "SELECT p_partkey, round(ln(p_retailprice), 6) AS a, round(log2(p_retailprice), 6) AS b, round(sqrt(p_retailprice), 6) AS c, CAST(floor(p_retailprice) AS BIGINT) AS f, CASE WHEN p_size % 7 = 0 THEN NULL ELSE round(p_retailprice / (p_size % 7), 6) END AS q, greatest(p_size, 10) AS g FROM part")
def _(s, d):
    p = F.col("p_retailprice")
    return T(s, d, "part").select("p_partkey", F.round(F.ln(p), 6).alias("a"), F.round(F.log2(p), 6).alias("b"), F.round(F.sqrt(p), 6).alias("c"), F.floor(p).alias("f"), F.round(F.try_divide(p, F.col("p_size") % 7), 6).alias("q"), F.greatest("p_size", F.lit(10)).alias("g"))


@R.add("op_array_functions", P.with_(P.E, select="SELECT id, round(list_sum(list_transform(v, lambda x: x * x)), 6) AS sq, len(list_filter(v, lambda x: x > 0)) AS pos, list_transform(list_sort(v)[1:3], lambda x: round(x, 6)) AS low, round(list_dot_product(v, v), 6) AS dot FROM e"))
def _(s, d):
    v = F.col("vec")
    return e_all(s, d).select(F.col("sample_id").alias("id"), F.round(F.aggregate(F.transform(v, lambda x: x * x), F.lit(0.0), lambda a, x: a + x), 6).alias("sq"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("pos"), F.transform(F.slice(F.array_sort(v), 1, 3), lambda x: F.round(x, 6)).alias("low"), F.round(F.aggregate(F.zip_with(v, v, lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x), 6).alias("dot"))


@R.add("op_array_explode", P.with_(P.E, select="SELECT label, pos - 1 AS pos, round(avg(x), 6) AS mean FROM (SELECT label, unnest(v) AS x, generate_subscripts(v, 1) AS pos FROM e) GROUP BY ALL"))
def _(s, d):
    return e_all(s, d).select("label", F.posexplode("vec").alias("pos", "x")).groupBy("label", F.col("pos").cast("long").alias("pos")).agg(F.round(F.avg("x"), 6).alias("mean"))


@R.add("op_map_functions", P.with_(P.E, f"q AS (SELECT id, {P.quantized('v')} AS lv FROM e)", "c AS (SELECT id, lv, count(*) AS n FROM (SELECT id, unnest(lv) AS lv FROM q) GROUP BY ALL)", select="SELECT id, list(lv ORDER BY lv) AS levels, CAST(sum(n) AS BIGINT) AS total FROM c WHERE n > 4 GROUP BY id"))
def _(s, d):
    lv = L.quantize_levels(F.col("vec"), 16, -0.5, 0.5)
    counts = e_all(s, d).select(F.col("sample_id").alias("id"), F.explode(lv).alias("lv")).groupBy("id", "lv").agg(F.count(F.lit(1)).alias("n"))
    m = counts.groupBy("id").agg(F.map_from_entries(F.collect_list(F.struct("lv", "n"))).alias("m")).select("id", F.map_filter("m", lambda k, n: n > 4).alias("m")).filter(F.size("m") > 0)
    return m.select("id", F.array_sort(F.map_keys("m")).alias("levels"), F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))


@R.add("op_json_extract", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def _(s, d):
    return T(s, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@R.add("op_sample_md5", f"SELECT doc_id FROM documents ORDER BY {P.hash_order('doc_id')}, doc_id LIMIT 100")
def _(s, d):
    return top_n(T(s, d, "documents").select("doc_id", (-hash_order("doc_id")).alias("k")), 100, "k", "doc_id").select("doc_id")


TENTH, HALF_ = 2**52 // 10, 2**52 // 2  # of the 52-bit hashes: samples that no partitioning changes


@R.add("op_sample_bernoulli", f"SELECT doc_id FROM documents WHERE {P.hash_order('doc_id')} < {TENTH}")
def _(s, d):
    return T(s, d, "documents").select("doc_id").filter(hash_order("doc_id") < TENTH)


@R.add("op_sample_stratified", f"SELECT doc_id, lang FROM documents WHERE {P.hash_order('doc_id')} < CASE WHEN lang = 'en' THEN {TENTH} ELSE {HALF_} END")
def _(s, d):
    return T(s, d, "documents").select("doc_id", "lang").filter(hash_order("doc_id") < F.when(F.col("lang") == "en", TENTH).otherwise(HALF_))


@R.add("op_dedup_exact", "SELECT min(doc_id) AS doc_id, count(*) AS n FROM documents GROUP BY text")
def _(s, d):
    return T(s, d, "documents").groupBy("text").agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("n")).select("doc_id", "n")


@R.add("op_dedup_normalized", r"SELECT min(doc_id) AS doc_id, count(*) AS n FROM documents GROUP BY md5(trim(regexp_replace(lower(text), '\s+', ' ', 'g')))")
def _(s, d):
    key = F.md5(F.trim(F.regexp_replace(F.lower("text"), r"\s+", " ")))
    return T(s, d, "documents").groupBy(key.alias("k")).agg(F.min("doc_id").alias("doc_id"), F.count(F.lit(1)).alias("n")).select("doc_id", "n")


@R.add("op_dedup_cosine", P.with_(P.E, P.Z, select="SELECT a.id AS a, b.id AS b, round(list_dot_product(a.z, b.z), 6) AS sim FROM z a JOIN z b ON a.id < b.id AND round(list_dot_product(a.z, b.z), 9) >= 0.45"))
def _(s, d):
    return similar_pairs(e_all(s, d), 0.45).select("a", "b", F.round("sim", 6).alias("sim"))


for _fmt in ("csv", "json", "orc"):

    @R.add(f"op_io_roundtrip_{_fmt}", "SELECT n_nationkey, n_name, n_regionkey FROM nation")
    def _(s, d, fmt=_fmt):
        import uuid

        df, path = T(s, d, "nation").select("n_nationkey", "n_name", "n_regionkey"), f"{work_dir(s)}/io-{uuid.uuid4().hex[:12]}"
        write(df, path, fmt)
        return read(s, path, fmt, df.schema)


@R.add("op_io_partitioned", "SELECT lang, doc_id FROM documents WHERE lang = 'fr'")
def _(s, d):
    import uuid

    path = f"{work_dir(s)}/io-{uuid.uuid4().hex[:12]}"
    write(T(s, d, "documents").select("doc_id", "lang"), path, "parquet", ("lang",))
    return s.read.parquet(path).filter("lang = 'fr'").select("lang", "doc_id")


@R.add("op_sql_parameters", P.with_(P.DOC_H, select="SELECT id AS sample_id, round(h, 6) AS entropy FROM dh WHERE h >= 2.95"))
def _(s, d):
    stage(s, sample_entropy(docs(s, d)), "h").createOrReplaceTempView("sl_scores")
    return s.sql("SELECT sample_id, round(entropy, 6) AS entropy FROM sl_scores WHERE entropy >= :tau", args={"tau": 2.95})
