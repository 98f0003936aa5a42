"""Relational operators that surround the method, each with its twin."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import relational as R
from ..operators.matrix import epoch
from ..plans import evaluate as E
from .registry import EV, cells, query, s6, u6


def _t(spark, d, name):
    return spark.read.parquet(f"{d}/{name}.parquet")


# ---- scans: every table, its rows and a fingerprint of its key ------------------------------------------------------

KEYS = {"region": "r_regionkey", "nation": "n_nationkey", "customer": "c_custkey", "supplier": "s_suppkey", "part": "p_partkey", "orders": "o_orderkey", "lineitem": "l_orderkey", "events": "event_id", "documents": "doc_id", "embeddings": "vec_id", "pages": "page_id", "benchmark": "item_id", "labels": "doc_id", "conversations": "conv_id"}
for _name, _key in KEYS.items():

    @query(f"SELECT count(*) AS n, count(DISTINCT {_key}) AS keys, sum({_key})::BIGINT AS total FROM {_name}", name=f"scan_{_name}")
    def _scan(spark, d, name=_name, key=_key):
        return _t(spark, d, name).agg(F.count(F.lit(1)).alias("n"), F.count_distinct(key).alias("keys"), F.sum(key).alias("total"))


# ---- filters ---------------------------------------------------------------------------------------------------------


@query("SELECT event_id, user_id FROM events WHERE value BETWEEN 10 AND 20 AND event_type IN ('click', 'view') AND user_id IS NOT NULL")
def filter_between_in(spark, d):
    return _t(spark, d, "events").where(F.col("value").between(10, 20) & F.col("event_type").isin("click", "view") & F.col("user_id").isNotNull()).select("event_id", "user_id")


@query("SELECT p_partkey, p_type FROM part WHERE p_type LIKE '%E%' AND NOT p_brand LIKE '%1'")
def filter_like(spark, d):
    return _t(spark, d, "part").where(F.col("p_type").like("%E%") & ~F.col("p_brand").like("%1")).select("p_partkey", "p_type")


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events WHERE CAST(json_extract_string(props, '$.k') AS BIGINT) < 7")
def json_props(spark, d):
    e = _t(spark, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k"))
    return e.where("k < 7")


@query("SELECT event_id FROM events WHERE ts >= TIMESTAMP '2024-01-05' AND ts < TIMESTAMP '2024-01-07'")
def filter_time_slice(spark, d):
    lo, hi = (F.lit(x).cast("timestamp_ntz") for x in ("2024-01-05 00:00:00", "2024-01-07 00:00:00"))
    return _t(spark, d, "events").where((F.col("ts") >= lo) & (F.col("ts") < hi)).select("event_id")


# ---- joins -----------------------------------------------------------------------------------------------------------

for _kind, _sql in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN")):

    @query(f"SELECT c_custkey, o_orderkey FROM customer {_sql} orders ON c_custkey = o_custkey AND o_totalprice <= c_acctbal", name=f"join_{_kind}")
    def _join(spark, d, kind=_kind):
        """Customers and the orders that their balance pays; both sides have rows without a partner."""
        pays = (F.col("c_custkey") == F.col("o_custkey")) & (F.col("o_totalprice") <= F.col("c_acctbal"))
        return _t(spark, d, "customer").join(_t(spark, d, "orders"), pays, kind).select("c_custkey", "o_orderkey")


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_semi(spark, d):
    return _t(spark, d, "customer").join(_t(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_anti(spark, d):
    return _t(spark, d, "customer").join(_t(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


_NATIONS = "SELECT r_name, n_name, count(*) AS suppliers FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2"


@query(_NATIONS)
def join_broadcast(spark, d):
    """The fact side stays where it is: nation and region have a fixed number of rows."""
    s, n, r = (_t(spark, d, x) for x in ("supplier", "nation", "region"))
    return s.join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name", "n_name").agg(F.count(F.lit(1)).alias("suppliers"))


for _hint in ("merge", "shuffle_hash"):

    @query("SELECT o_orderkey, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1", name=f"join_{_hint}")
    def _hinted(spark, d, hint=_hint):
        return _t(spark, d, "lineitem").join(_t(spark, d, "orders").hint(hint), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey").agg(F.count(F.lit(1)).alias("lines"))


@query(f"WITH {cells('type')} SELECT a.win_id, a.entity AS i, b.entity AS j FROM cells a JOIN cells b ON a.win_id = b.win_id AND a.feature = b.feature AND a.entity < b.entity AND a.x = b.x AND a.x >= 3")
def join_theta(spark, d):
    c = E.log_cells(spark, d, "type").where("x >= 3")
    a, b = (c.select("win_id", "feature", "x", F.col("entity").alias(e)) for e in "ij")
    return a.join(b, ["win_id", "feature", "x"]).where("i < j").select("win_id", "i", "j")


@query("SELECT o_orderkey, lo FROM orders JOIN (SELECT unnest([0, 50000, 100000, 200000]) AS lo, unnest([50000, 100000, 200000, 1000000]) AS hi) b ON o_totalprice >= lo AND o_totalprice < hi")
def join_range(spark, d):
    b = spark.createDataFrame([(0, 50_000), (50_000, 100_000), (100_000, 200_000), (200_000, 1_000_000)], "lo long, hi long")
    return R.point_join(_t(spark, d, "orders").select("o_orderkey", F.col("o_totalprice").alias("x")), b, 50_000).select("o_orderkey", "lo")




@query(f"WITH {EV}, iv AS (SELECT entity, at_s - at_s % 86400 AS day, min(at_s) AS lo, min(at_s) + 900 AS hi FROM ev GROUP BY 1, 2) SELECT a.entity AS a_id, b.entity AS b_id, a.day FROM iv a JOIN iv b ON a.lo < b.hi AND b.lo < a.hi AND a.day = b.day AND a.entity < b.entity")
def join_interval(spark, d):
    """Users whose first quarter hours of a day overlap."""
    e = _t(spark, d, "events").select(F.col("user_id").alias("entity"), epoch(F.col("ts")).alias("at_s"))
    iv = e.groupBy("entity", (F.col("at_s") - F.col("at_s") % 86_400).alias("day")).agg(F.min("at_s").alias("lo"))
    side = lambda p: iv.select(F.col("entity").alias(f"{p}_id"), F.col("day").alias(f"{p}_day"), F.col("lo").alias(f"{p}_lo"), (F.col("lo") + 900).alias(f"{p}_hi"))
    return R.overlap_join(side("a"), side("b"), 900).where("a_day = b_day and a_id < b_id").select("a_id", "b_id", F.col("a_day").alias("day"))


@query("WITH p AS (SELECT l_partkey AS part, CAST(epoch(l_shipdate) AS BIGINT) AS t, max(l_extendedprice / l_quantity) AS price FROM lineitem GROUP BY 1, 2), q AS (SELECT o_orderkey, CAST(epoch(o_orderdate) AS BIGINT) AS t, (o_orderkey % (SELECT max(p_partkey) FROM part)) + 1 AS part FROM orders) SELECT q.o_orderkey, q.part, q.t, CAST(floor(p.price * 1000000 + 0.5) AS BIGINT) AS price_u6 FROM q ASOF LEFT JOIN p ON q.part = p.part AND q.t >= p.t")
def join_asof(spark, d):
    """The last known price of a part at each order's time."""
    top = _t(spark, d, "part").agg(F.max("p_partkey")).first()[0] or 1
    prices = _t(spark, d, "lineitem").select(F.col("l_partkey").alias("part"), epoch(F.col("l_shipdate").cast("timestamp_ntz")).alias("u"), (F.col("l_extendedprice") / F.col("l_quantity")).alias("price"))
    asked = _t(spark, d, "orders").select("o_orderkey", epoch(F.col("o_orderdate").cast("timestamp_ntz")).alias("t"), (F.col("o_orderkey") % top + 1).alias("part"))
    return R.asof_join(asked, prices, "part", "t", "u", "price").select("o_orderkey", "part", "t", u6("price").alias("price_u6"))


@query("SELECT r_regionkey, q FROM region, (SELECT unnest(generate_series(1, 4)) AS q)")
def join_cross(spark, d):
    """A calendar of four quarters for each region: both sides of a fixed size."""
    return _t(spark, d, "region").select("r_regionkey").crossJoin(F.broadcast(spark.range(1, 5).select(F.col("id").alias("q"))))


# ---- aggregates ------------------------------------------------------------------------------------------------------


@query(f"SELECT l_returnflag, l_linestatus, count(*) AS n, {s6('sum(l_quantity) / 1000')} AS qty_u6, {s6('avg(l_discount)')} AS disc_u6, min(l_partkey) AS p0, max(l_partkey) AS p1 FROM lineitem GROUP BY 1, 2")
def agg_hash(spark, d):
    return _t(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), u6(F.sum("l_quantity") / 1000).alias("qty_u6"), u6(F.avg("l_discount")).alias("disc_u6"), F.min("l_partkey").alias("p0"), F.max("l_partkey").alias("p1"))


@query("SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def agg_distinct(spark, d):
    return _t(spark, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query()
def agg_approx_distinct(spark, d):
    return _t(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", 0.5, 1000).alias("median"))


@query(f"SELECT event_type, {s6('median(value)')} AS median_u6, {s6('quantile_cont(value, 0.9)')} AS p90_u6 FROM events GROUP BY 1")
def agg_percentile(spark, d):
    return _t(spark, d, "events").groupBy("event_type").agg(u6(F.median("value")).alias("median_u6"), u6(F.percentile("value", 0.9)).alias("p90_u6"))


@query("SELECT event_type, CAST(floor(corr(value, event_id) * 10000 + 0.5) AS BIGINT) AS corr_e4, CAST(floor(covar_samp(value, event_id) / 1000 + 0.5) AS BIGINT) AS cov_k, max_by(event_id, struct_pack(a := value, b := event_id)) AS top FROM events GROUP BY 1")
def agg_corr(spark, d):
    return _t(spark, d, "events").groupBy("event_type").agg(F.floor(F.corr("value", "event_id") * 10000 + 0.5).alias("corr_e4"), F.floor(F.covar_samp("value", "event_id") / 1000 + 0.5).alias("cov_k"), F.max_by("event_id", F.struct("value", "event_id")).alias("top"))


_DIM = "SELECT coalesce(n_name, '*') AS nation, coalesce(c_mktsegment, '*') AS segment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY "


def _dim(spark, d):
    return _t(spark, d, "customer").join(F.broadcast(_t(spark, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))


def _stars(x):
    return x.agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("n_name", F.lit("*")).alias("nation"), F.coalesce("c_mktsegment", F.lit("*")).alias("segment"), "n")


@query(_DIM + "ROLLUP (n_name, c_mktsegment)")
def agg_rollup(spark, d):
    return _stars(_dim(spark, d).rollup("n_name", "c_mktsegment"))


@query(_DIM + "CUBE (n_name, c_mktsegment)")
def agg_cube(spark, d):
    return _stars(_dim(spark, d).cube("n_name", "c_mktsegment"))


@query(_DIM + "GROUPING SETS ((n_name), (c_mktsegment), ())")
def agg_grouping_sets(spark, d):
    _dim(spark, d).select("n_name", "c_mktsegment").createOrReplaceTempView("_dim")
    return spark.sql("SELECT coalesce(n_name, '*') AS nation, coalesce(c_mktsegment, '*') AS segment, count(*) AS n FROM _dim GROUP BY GROUPING SETS ((n_name), (c_mktsegment), ())")


_PIVOT = "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events WHERE event_type IN ('click', 'view') GROUP BY 1"


@query(f"SELECT user_id, nullif(click, 0) AS click, nullif(view, 0) AS view FROM ({_PIVOT})")
def agg_pivot(spark, d):
    return _t(spark, d, "events").where("event_type in ('click', 'view')").groupBy("user_id").pivot("event_type", ["click", "view"]).count()


@query(f"SELECT user_id, 'click' AS kind, click AS n FROM ({_PIVOT}) UNION ALL SELECT user_id, 'view', view FROM ({_PIVOT})")
def agg_unpivot(spark, d):
    return agg_pivot(spark, d).fillna(0).unpivot(["user_id"], ["click", "view"], "kind", "n")


# ---- windows ---------------------------------------------------------------------------------------------------------



def _w():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


_RANKS = {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank}
for _f, _fn in _RANKS.items():

    @query(f"SELECT event_id, {_f}() OVER (PARTITION BY user_id ORDER BY event_type) AS r FROM events" if _f != "row_number" else "SELECT event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS r FROM events", name=f"win_{_f}")
    def _rank(spark, d, f=_f, fn=_fn):
        w = _w() if f == "row_number" else Window.partitionBy("user_id").orderBy("event_type")
        return _t(spark, d, "events").select("event_id", fn().over(w).cast("long").alias("r"))


@query(f"SELECT event_id, ntile(4) OVER w AS quarter, {s6('percent_rank() OVER w')} AS pr_u6, {s6('cume_dist() OVER w')} AS cd_u6 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_ntile(spark, d):
    return _t(spark, d, "events").select("event_id", F.ntile(4).over(_w()).cast("long").alias("quarter"), u6(F.percent_rank().over(_w())).alias("pr_u6"), u6(F.cume_dist().over(_w())).alias("cd_u6"))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after, first_value(event_id) OVER w AS first_, last_value(event_id) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_, nth_value(event_id, 2) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark, d):
    whole = _w().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _t(spark, d, "events").select("event_id", F.lag("event_id").over(_w()).alias("before"), F.lead("event_id", 2).over(_w()).alias("after"), F.first("event_id").over(_w()).alias("first_"), F.last("event_id").over(whole).alias("last_"), F.nth_value("event_id", 2).over(whole).alias("second"))


@query(f"WITH {cells('type')} SELECT win_id, entity, feature, sum(x) OVER (PARTITION BY entity, feature ORDER BY win_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS rows3, sum(x) OVER (PARTITION BY entity, feature ORDER BY win_id RANGE BETWEEN 172800 PRECEDING AND CURRENT ROW)::BIGINT AS days3, sum(x) OVER (PARTITION BY entity, feature ORDER BY win_id ROWS UNBOUNDED PRECEDING)::BIGINT AS run FROM cells")
def win_frames(spark, d):
    w = Window.partitionBy("entity", "feature").orderBy("win_id")
    s = F.sum("x")
    return E.log_cells(spark, d, "type").select("win_id", "entity", "feature", s.over(w.rowsBetween(-2, 0)).alias("rows3"), s.over(w.rangeBetween(-172_800, 0)).alias("days3"), s.over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("run"))


@query("SELECT win_id, entity, total FROM (WITH " + cells("type") + " SELECT win_id, entity, sum(x)::BIGINT AS total FROM cells GROUP BY 1, 2) QUALIFY row_number() OVER (PARTITION BY win_id ORDER BY total DESC, entity) <= 3")
def topk_per_window(spark, d):
    x = E.log_cells(spark, d, "type").groupBy("win_id", "entity").agg(F.sum("x").alias("total"))
    return x.withColumn("r", F.row_number().over(Window.partitionBy("win_id").orderBy(F.desc("total"), "entity"))).where("r <= 3").drop("r")


@query(f"WITH {cells('type')} SELECT win_id, sum(x)::BIGINT AS total FROM cells GROUP BY 1 ORDER BY total DESC, win_id LIMIT 5")
def topk_windows(spark, d):
    return E.log_cells(spark, d, "type").groupBy("win_id").agg(F.sum("x").alias("total")).orderBy(F.desc("total"), "win_id").limit(5)


# ---- sets ------------------------------------------------------------------------------------------------------------

_A, _B = "SELECT user_id, event_type FROM events WHERE event_id % 2 = 0", "SELECT user_id, event_type FROM events WHERE event_id % 3 = 0"
for _name, _sql, _op in (("union_all", "UNION ALL", "unionByName"), ("intersect", "INTERSECT", "intersect"), ("intersect_all", "INTERSECT ALL", "intersectAll"), ("except_all", "EXCEPT ALL", "exceptAll"), ("except_distinct", "EXCEPT", "subtract")):

    @query(f"{_A} {_sql} {_B}", name=_name)
    def _set(spark, d, op=_op):
        e = _t(spark, d, "events").select("event_id", "user_id", "event_type")
        a, b = (e.where(f"event_id % {k} = 0").select("user_id", "event_type") for k in (2, 3))
        return getattr(a, op)(b)


@query(f"{_A} UNION {_B}")
def union_distinct(spark, d):
    e = _t(spark, d, "events").select("event_id", "user_id", "event_type")
    return e.where("event_id % 2 = 0 or event_id % 3 = 0").select("user_id", "event_type").distinct()


# ---- functions -------------------------------------------------------------------------------------------------------


@query("SELECT page_id, lower(regexp_extract(url, '://([^/?#]+)', 1)) AS host, md5(url) AS m, upper(substring(url, 1, 5)) AS s, length(url) AS n, replace(url, '/', '|') AS r FROM pages")
def str_urls(spark, d):
    u = F.col("url")
    return _t(spark, d, "pages").select("page_id", F.lower(F.regexp_extract(u, "://([^/?#]+)", 1)).alias("host"), F.md5(u).alias("m"), F.upper(F.substring(u, 1, 5)).alias("s"), F.length(u).cast("long").alias("n"), F.replace(u, F.lit("/"), F.lit("|")).alias("r"))


@query("SELECT doc_id, len(regexp_extract_all(text, '[a-z]+')) AS words, len(string_split(text, chr(10))) AS lines FROM documents")
def str_words(spark, d):
    return _t(spark, d, "documents").select("doc_id", F.size(F.regexp_extract_all("text", F.lit("[a-z]+"), F.lit(0))).cast("long").alias("words"), F.size(F.split("text", "\n")).cast("long").alias("lines"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, quarter(o_orderdate) AS q, dayofweek(o_orderdate) + 1 AS dow, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days, CAST(date_trunc('month', o_orderdate) AS DATE) AS month FROM orders")
def date_parts(spark, d):
    t = F.col("o_orderdate")
    return _t(spark, d, "orders").select("o_orderkey", F.year(t).cast("long").alias("y"), F.quarter(t).cast("long").alias("q"), F.dayofweek(t).cast("long").alias("dow"), F.date_diff(F.to_date(t), F.lit("1995-01-01").cast("date")).cast("long").alias("days"), F.to_date(F.date_trunc("month", t)).alias("month"))


@query(f"SELECT event_id, {s6('sqrt(value)')} AS r_u6, {s6('ln(value + 1)')} AS l_u6, {s6('pow(value, 1.4::DOUBLE) / 1000')} AS p_u6, CAST(floor(value) AS BIGINT) AS f, CAST(ceil(value) AS BIGINT) AS c, {s6('least(value, 50)')} AS m_u6 FROM events")
def math_functions(spark, d):
    v = F.col("value")
    return _t(spark, d, "events").select("event_id", u6(F.sqrt(v)).alias("r_u6"), u6(F.ln(v + 1)).alias("l_u6"), u6(F.pow(v, F.lit(1.4)) / 1000).alias("p_u6"), F.floor(v).alias("f"), F.ceil(v).alias("c"), u6(F.least(v, F.lit(50.0))).alias("m_u6"))


@query(f"SELECT vec_id, {s6('list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))')} AS norm_u6, {s6('list_max(embedding)::DOUBLE')} AS top_u6, len(list_filter(embedding, lambda x: x > 0)) AS positive FROM embeddings")
def arr_functions(spark, d):
    e = F.col("embedding")
    dot = F.aggregate(e, F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
    return _t(spark, d, "embeddings").select("vec_id", u6(dot).alias("norm_u6"), u6(F.array_max(e).cast("double")).alias("top_u6"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"))


@query(f"WITH {cells()} SELECT win_id, entity, count(*) AS features, sum(x)::BIGINT AS total, max(x) AS top FROM cells GROUP BY 1, 2")
def map_columns(spark, d):
    """Sparse columns as maps, summed without leaving the map."""
    m = E.log_cells(spark, d).groupBy("win_id", "entity").agg(F.map_from_entries(F.collect_list(F.struct("feature", "x"))).alias("m"))
    v = F.map_values("m")
    return m.select("win_id", "entity", F.size("m").cast("long").alias("features"), F.aggregate(v, F.lit(0).cast("long"), lambda s, x: s + x).alias("total"), F.array_max(v).alias("top"))


@query("SELECT conv_id, count(*) AS turns, string_agg(role, '>' ORDER BY turn, role) AS roles FROM conversations GROUP BY 1")
def arr_ordered_roles(spark, d):
    c = _t(spark, d, "conversations").groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role"))).alias("a"))
    return c.select("conv_id", F.size("a").cast("long").alias("turns"), F.array_join(F.transform("a", lambda s: s["role"]), ">").alias("roles"))


@query()
def sample_rows(spark, d):
    """Bernoulli and stratified samples of the stream."""
    e = _t(spark, d, "events")
    a = e.sample(fraction=0.1, seed=3).groupBy("event_type").agg(F.count(F.lit(1)).alias("bernoulli"))
    b = e.sampleBy("event_type", {"click": 0.5, "view": 0.1}, seed=3).groupBy("event_type").agg(F.count(F.lit(1)).alias("stratified"))
    return a.join(b, "event_type", "left")


@query()
def ml_correlation(spark, d):
    """The library's correlation matrix of the embeddings' first dimensions, largest entry off the diagonal."""
    from pyspark.ml.functions import array_to_vector
    from pyspark.ml.stat import Correlation

    e = _t(spark, d, "embeddings").select(array_to_vector(F.slice("embedding", 1, 8).cast("array<double>")).alias("v"))
    m = Correlation.corr(e, "v").first()[0].toArray()
    return spark.createDataFrame([(i, j, float(m[i, j])) for i in range(8) for j in range(i)], "i int, j int, rho double")
