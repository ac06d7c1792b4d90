"""Relational operators, sources and functions around the methods: each a Spark query with its SQL twin."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from .sources.tables import event_points, micros, new_path, table

QUERIES: dict = {}
ORACLES: dict = {}


def query(sql: str | None = None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return keep


POINTS = "select event_id as oid, (epoch_us(ts) - 1704067200000000) / 2592000000000.0::double as x, value / 100 as y from events where ts is not null and value is not null"


@query("select l_orderkey, l_partkey, l_quantity from lineitem")
def scan_project(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")


def _round_trip(spark, d, fmt: str, **options) -> DataFrame:
    flat = event_points(spark, d).select("oid", F.col("obj")[0].alias("x"), F.col("obj")[1].alias("y"))
    path = new_path(spark, f"round-trip-{fmt}")
    flat.write.format(fmt).options(**options).save(path)
    return spark.read.schema("oid long, x double, y double").options(**options).format(fmt).load(path)


@query(POINTS)
def io_roundtrip_csv(spark, d):
    return _round_trip(spark, d, "csv")


@query(POINTS)
def io_roundtrip_json(spark, d):
    return _round_trip(spark, d, "json")


@query(POINTS)
def io_roundtrip_orc(spark, d):
    return _round_trip(spark, d, "orc")


@query(POINTS)
def project_points(spark, d):
    return event_points(spark, d).selectExpr("oid", "obj[0] as x", "obj[1] as y")


@query("select o_orderkey, o_totalprice from orders where o_totalprice between 100000 and 200000")
def filter_between(spark, d):
    return table(spark, d, "orders").where(F.col("o_totalprice").between(100000, 200000)).select("o_orderkey", "o_totalprice")


@query("select o_orderkey, o_orderpriority from orders where o_orderpriority in ('1-URGENT', '2-HIGH') and o_orderstatus is not distinct from 'F'")
def filter_in(spark, d):
    return table(spark, d, "orders").where(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH") & F.col("o_orderstatus").eqNullSafe("F")).select("o_orderkey", "o_orderpriority")


@query("select p_partkey, p_name from part where p_name like '%a%e%'")
def filter_like(spark, d):
    return table(spark, d, "part").where(F.col("p_name").like("%a%e%")).select("p_partkey", "p_name")


@query("select r_name, count(*) as n, round(sum(c_acctbal), 2) as balance from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name")
def join_broadcast(spark, d):
    c, n, r = (table(spark, d, t) for t in ("customer", "nation", "region"))
    j = c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey)
    return j.groupBy("r_name").agg(F.count("*").alias("n"), F.round(F.sum("c_acctbal"), 2).alias("balance"))


_ORDERS_LINES = "select o_orderpriority, count(*) as n, round(sum(l_quantity), 2) as quantity from orders join lineitem on o_orderkey = l_orderkey group by o_orderpriority"


def _orders_lines(spark, d, hint: str):
    o, li = table(spark, d, "orders"), table(spark, d, "lineitem")
    return li.join(o.hint(hint), li.l_orderkey == o.o_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query(_ORDERS_LINES)
def join_sort_merge(spark, d):
    return _orders_lines(spark, d, "merge")


@query(_ORDERS_LINES)
def join_shuffle_hash(spark, d):
    return _orders_lines(spark, d, "shuffle_hash")


@query(f"with p as ({POINTS}) select q.oid as qid, c.oid as cid from p q join p c on sqrt((q.x - c.x) * (q.x - c.x) + (q.y - c.y) * (q.y - c.y)) <= 0.005 + 0.01 where q.oid % 50 = 0")
def join_theta(spark, d):
    """Pairs within a distance meet through an equi join on the nine cells around a query, then the exact test."""
    p = event_points(spark, d).select("oid", F.col("obj")[0].alias("x"), F.col("obj")[1].alias("y"))
    side = (0.005 + 0.01) * (1 + 1e-6)  # a little over the distance, so that rounding moves no pair more than one cell apart
    at = lambda c: F.floor(F.col(c) / F.lit(side))
    near = lambda c: F.explode(F.sequence(at(c) - 1, at(c) + 1))
    q = p.where("oid % 50 = 0").select("*", near("x").alias("i")).select("*", near("y").alias("j")).alias("q")
    c = p.select("*", at("x").alias("i"), at("y").alias("j")).alias("c")
    dist = F.expr("sqrt((q.x - c.x) * (q.x - c.x) + (q.y - c.y) * (q.y - c.y))")
    found = c.join(q.hint("shuffle_hash"), (F.col("q.i") == F.col("c.i")) & (F.col("q.j") == F.col("c.j")) & (dist <= F.lit(0.005) + F.lit(0.01)))
    return found.select(F.col("q.oid").alias("qid"), F.col("c.oid").alias("cid"))


@query("with r as (select o_custkey as k, o_totalprice as lo, o_totalprice + 50 as hi from orders where o_orderkey % 50 = 0) select k, lo, o_orderkey from r join orders on o_totalprice between lo and hi")
def join_range(spark, d):
    """Intervals meet keys through an equi join on buckets of the interval's width, then the exact test."""
    o = table(spark, d, "orders")
    width = 50.0
    b = lambda c: F.floor(c / width)
    r = o.where("o_orderkey % 50 = 0").select(F.col("o_custkey").alias("k"), F.col("o_totalprice").alias("lo"), (F.col("o_totalprice") + 50).alias("hi"))
    r = r.withColumn("b", F.explode(F.sequence(b(F.col("lo")), b(F.col("hi")))))
    keyed = o.select("o_orderkey", "o_totalprice", b(F.col("o_totalprice")).alias("ob"))
    return keyed.join(r, (F.col("ob") == F.col("b")) & F.col("o_totalprice").between(F.col("lo"), F.col("hi"))).select("k", "lo", "o_orderkey")


@query("select event_id, (select max(b.event_id) from events b where b.user_id = a.user_id and b.event_type = 'click' and b.event_id < a.event_id) as last_click from events a where event_type = 'purchase'")
def asof_event(spark, d):
    """The last click of the user before each purchase: one window, no inequality join. event_id rises with time."""
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    e = table(spark, d, "events").withColumn("last_click", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(w))
    return e.where("event_type = 'purchase'").select("event_id", "last_click")


@query("select c_custkey, o_orderkey from customer left join (select * from orders where o_totalprice > 400000) on c_custkey = o_custkey")
def join_left(spark, d):
    c, o = table(spark, d, "customer"), table(spark, d, "orders").where("o_totalprice > 400000")
    return c.join(o, c.c_custkey == o.o_custkey, "left").select("c_custkey", "o_orderkey")


@query("select s_suppkey, c_custkey from supplier full join customer on s_suppkey = 2 * c_custkey")
def join_full(spark, d):
    """Suppliers of odd keys and customers of large ones have no partner."""
    s, c = table(spark, d, "supplier"), table(spark, d, "customer")
    return s.join(c, s.s_suppkey == 2 * c.c_custkey, "full").select("s_suppkey", "c_custkey")


@query("select r_name, n_name from region cross join nation")
def join_cross(spark, d):
    """Two tables of fixed size."""
    return table(spark, d, "region").crossJoin(F.broadcast(table(spark, d, "nation"))).select("r_name", "n_name")


@query(f"with p as ({POINTS}) select q.oid as qid, o.oid from p q join p o on abs(o.x - q.x) <= 0.01 and abs(o.y - q.y) <= 0.01 where q.oid % 50 = 0")
def lateral_mrq(spark, d):
    event_points(spark, d).selectExpr("oid", "obj[0] as x", "obj[1] as y").createOrReplaceTempView("lateral_points")
    return spark.sql("select q.oid as qid, t.oid from (select * from lateral_points where oid % 50 = 0) q, lateral (select o.oid from lateral_points o where abs(o.x - q.x) <= 0.01D and abs(o.y - q.y) <= 0.01D) t")


@query("select l_returnflag, l_linestatus, count(*) as n, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from lineitem group by all")
def agg_hash(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query("with w as (select distinct t as w from (select unnest(regexp_split_to_array(lower(text), '\\s+')) as t from documents) where regexp_full_match(t, '[a-z]{1,34}')) select w[1] as letter, min(w) as first_word, max(w) as last_word, max(length(w))::integer as longest from w group by 1")
def agg_sort(spark, d):
    from .sources.tables import words

    return words(spark, d).groupBy(F.substring("obj", 1, 1).alias("letter")).agg(F.min("obj").alias("first_word"), F.max("obj").alias("last_word"), F.max(F.length("obj")).alias("longest"))


@query("select event_type, count(distinct user_id) as users from events group by event_type")
def agg_distinct(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"))


@query()
def agg_approx_distinct(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


_GROUPED = "select event_type, user_id % 5 as user_group, count(*) as n from events group by {}"


def _events_grouped(spark, d):
    return table(spark, d, "events").withColumn("user_group", F.col("user_id") % 5)


@query(_GROUPED.format("rollup(event_type, user_id % 5)"))
def agg_rollup(spark, d):
    return _events_grouped(spark, d).rollup("event_type", "user_group").agg(F.count("*").alias("n"))


@query(_GROUPED.format("cube(event_type, user_id % 5)"))
def agg_cube(spark, d):
    return _events_grouped(spark, d).cube("event_type", "user_group").agg(F.count("*").alias("n"))


@query(_GROUPED.format("grouping sets ((event_type), (user_id % 5))"))
def agg_grouping_sets(spark, d):
    e = _events_grouped(spark, d)
    return e.groupingSets([[F.col("event_type")], [F.col("user_group")]], F.col("event_type"), F.col("user_group")).agg(F.count("*").alias("n"))


@query("select event_type, max(value) as radius from events group by event_type")
def agg_radius(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.max("value").alias("radius"))


@query("select o_custkey, arg_min(o_orderkey, o_totalprice) as cheapest from orders group by o_custkey")
def agg_min_by(spark, d):
    return table(spark, d, "orders").groupBy("o_custkey").agg(F.min_by("o_orderkey", "o_totalprice").alias("cheapest"))


@query("select event_type, round(var_pop(value), 4) as variance, round(avg(value), 4) as mean from events group by event_type")
def agg_var_pop(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.round(F.var_pop("value"), 4).alias("variance"), F.round(F.avg("value"), 4).alias("mean"))


@query("select event_type, round(quantile_cont(value, 0.25), 6) as q25, round(quantile_cont(value, 0.5), 6) as q50 from events group by event_type")
def agg_percentile(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.25)), 6).alias("q25"), F.round(F.percentile("value", F.lit(0.5)), 6).alias("q50"))


@query("select user_id % 10 as g, count(*) filter (event_type = 'click') as click, count(*) filter (event_type = 'purchase') as purchase, count(*) filter (event_type = 'error') as error from events group by 1")
def agg_pivot(spark, d):
    e = table(spark, d, "events").withColumn("g", F.col("user_id") % 10)
    p = e.groupBy("g").pivot("event_type", ["click", "purchase", "error"]).agg(F.count(F.lit(1)))
    return p.select("g", *[F.coalesce(c, F.lit(0)).alias(c) for c in ("click", "purchase", "error")])


_RANKED = "select o_orderkey, {} as r from orders"
_BY = "over (partition by o_custkey order by o_totalprice, o_orderkey)"


def _ranked(spark, d, f):
    return table(spark, d, "orders").select("o_orderkey", f.over(Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")).alias("r"))


@query(_RANKED.format(f"(row_number() {_BY})::integer"))
def win_row_number(spark, d):
    return _ranked(spark, d, F.row_number())


@query("select o_orderkey, (rank() over (partition by o_custkey order by o_orderpriority))::integer as r from orders")
def win_rank(spark, d):
    return table(spark, d, "orders").select("o_orderkey", F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("r"))


@query("select o_orderkey, (dense_rank() over (partition by o_custkey order by o_orderpriority))::integer as r from orders")
def win_dense_rank(spark, d):
    return table(spark, d, "orders").select("o_orderkey", F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("r"))


@query(_RANKED.format(f"(ntile(4) {_BY})::integer"))
def win_ntile(spark, d):
    return _ranked(spark, d, F.ntile(4))


@query("select event_id, lag(value) over w as before, lead(value) over w as after from events window w as (partition by user_id order by event_id)")
def win_lag_lead(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return table(spark, d, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"))


@query("select event_id, first_value(value) over w as first, last_value(value) over w as last from events window w as (partition by user_id order by event_id rows between unbounded preceding and unbounded following)")
def win_first_last(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, d, "events").select("event_id", F.first("value").over(w).alias("first"), F.last("value").over(w).alias("last"))


@query("select event_id, round(avg(value) over (partition by user_id order by event_id rows between 2 preceding and current row), 6) as mean3 from events")
def win_rows_frame(spark, d):
    return table(spark, d, "events").select("event_id", F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(-2, 0)), 6).alias("mean3"))


@query("select event_id, count(*) over (partition by user_id order by event_id range between 1000 preceding and current row) as n from events")
def win_range_frame(spark, d):
    return table(spark, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy("event_id").rangeBetween(-1000, 0)).alias("n"))


@query("with p as (select c_nationkey as pid, count(*) as n from customer group by 1) select pid, n, (sum(n) over (order by n, pid))::bigint as fill from p")
def win_running_fill(spark, d):
    """Running size in key order, as packing uses it: one row a partition."""
    p = table(spark, d, "customer").groupBy(F.col("c_nationkey").alias("pid")).agg(F.count("*").alias("n"))
    return p.select("pid", "n", F.sum("n").over(Window.orderBy("n", "pid")).alias("fill"))


@query("select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10")
def topk_global(spark, d):
    return table(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


@query("select o_custkey, o_orderkey from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as r from orders) where r <= 2")
def topk_per_query(spark, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, d, "orders").withColumn("r", F.row_number().over(w)).where("r <= 2").select("o_custkey", "o_orderkey")


@query("select c_custkey, c_acctbal from customer order by c_acctbal, c_custkey limit 20 offset 10")
def sort_limit_offset(spark, d):
    return table(spark, d, "customer").orderBy("c_acctbal", "c_custkey").offset(10).limit(20).select("c_custkey", "c_acctbal")


def _near(spark, d, r: float):
    """(qid, oid) of the event points within r of one query point."""
    p = event_points(spark, d).select("oid", F.col("obj")[0].alias("x"), F.col("obj")[1].alias("y"))
    q = p.where("oid = 97").select(F.col("oid").alias("qid"), F.col("x").alias("qx"), F.col("y").alias("qy"))
    return p.crossJoin(F.broadcast(q)).where(F.sqrt((F.col("x") - F.col("qx")) ** 2 + (F.col("y") - F.col("qy")) ** 2) <= r).select("qid", "oid")


_NEAR = "select q.oid as qid, p.oid from p join p q on q.oid = 97 where sqrt((p.x - q.x) * (p.x - q.x) + (p.y - q.y) * (p.y - q.y)) <= {}"


def _sets(op: str) -> str:
    return f"with p as ({POINTS}) {_NEAR.format(0.1)} {op} {_NEAR.format(0.05)}"


@query(_sets("union all"))
def set_union(spark, d):
    return _near(spark, d, 0.1).union(_near(spark, d, 0.05))


@query(_sets("union"))
def set_union_distinct(spark, d):
    return _near(spark, d, 0.1).union(_near(spark, d, 0.05)).distinct()


@query(_sets("intersect"))
def set_intersect(spark, d):
    return _near(spark, d, 0.1).intersect(_near(spark, d, 0.05))


@query(_sets("except"))
def set_except(spark, d):
    return _near(spark, d, 0.1).subtract(_near(spark, d, 0.05))


@query(_sets("except all"))
def set_except_all(spark, d):
    return _near(spark, d, 0.1).exceptAll(_near(spark, d, 0.05))


@query("with w as (select distinct t as w from (select unnest(regexp_split_to_array(lower(text), '\\s+')) as t from documents) where regexp_full_match(t, '[a-z]{1,34}')) select w, upper(w) as up, length(w)::integer as n, replace(w, 'a', '_') as no_a, md5(w) as digest, levenshtein(w, 'there')::integer as d from w")
def fn_string(spark, d):
    from .sources.tables import words

    return words(spark, d).select(F.col("obj").alias("w"), F.upper("obj").alias("up"), F.length("obj").alias("n"), F.replace("obj", F.lit("a"), F.lit("_")).alias("no_a"), F.md5("obj").alias("digest"), F.levenshtein("obj", F.lit("there")).alias("d"))


@query("select o_orderkey, date_diff('day', date '1995-01-01', o_orderdate::date)::integer as days, year(o_orderdate)::integer as y, month(o_orderdate)::integer as m, epoch_us(o_orderdate) as us from orders")
def fn_date(spark, d):
    o, day = table(spark, d, "orders"), F.col("o_orderdate").cast("date")
    return o.select("o_orderkey", F.datediff(day, F.lit("1995-01-01").cast("date")).alias("days"), F.year(day).alias("y"), F.month(day).alias("m"), micros(F.col("o_orderdate")).alias("us"))


@query("select l_orderkey, l_linenumber, l_partkey, round(sqrt(l_quantity), 9) as s, abs(l_tax - 0.04) as a, floor(l_extendedprice / 1000)::bigint as f, l_partkey % 7 as p, greatest(l_discount, l_tax) as g, round(ln(l_quantity), 9) as l from lineitem")
def fn_math(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.round(F.sqrt("l_quantity"), 9).alias("s"), F.abs(F.col("l_tax") - 0.04).alias("a"), F.floor(F.col("l_extendedprice") / 1000).alias("f"), F.pmod("l_partkey", F.lit(7)).alias("p"), F.greatest("l_discount", "l_tax").alias("g"), F.round(F.log("l_quantity"), 9).alias("l"))


@query("select vec_id, len(embedding)::integer as n, round(list_max(embedding)::double, 6) as top, round(list_sum(list_transform(embedding, lambda x: abs(x::double))), 6) as l1, len(list_filter(embedding, lambda x: x > 0.1))::integer as big, embedding[3]::double as third from embeddings")
def fn_array(spark, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    return table(spark, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(F.array_max(e), 6).alias("top"), F.round(F.aggregate(F.transform(e, F.abs), F.lit(0.0), lambda a, x: a + x), 6).alias("l1"), F.size(F.filter("embedding", lambda x: x > 0.1)).alias("big"), F.element_at(e, 3).alias("third"))


@query("select doc_id, c as letter, (length(lower(text)) - length(replace(lower(text), c, '')))::integer as n from documents, (select unnest(['a', 'e', 'i', 'o', 'u']) as c)")
def fn_map(spark, d):
    low = F.lower("text")
    vowels = ["a", "e", "i", "o", "u"]
    m = F.map_from_arrays(F.array(*map(F.lit, vowels)), F.array(*[F.length(low) - F.length(F.replace(low, F.lit(c), F.lit(""))) for c in vowels]))
    return table(spark, d, "documents").select("doc_id", F.explode(m).alias("letter", "n"))


@query("select event_id, cast(json_extract(props, '$.k') as bigint) as k, cast(json_extract(props, '$.k') as double) / 100 as coordinate from events")
def fn_json(spark, d):
    k = F.from_json("props", "k bigint")["k"]
    return table(spark, d, "events").select("event_id", k.alias("k"), (F.get_json_object("props", "$.k").cast("double") / 100).alias("coordinate"))


@query("""
    with j as (select r_name, c_custkey, o_orderkey, abs(o_totalprice - 150000.0) as dist, row_number() over (partition by c_custkey order by abs(o_totalprice - 150000.0), o_orderkey) as r
               from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)
    select r_name, count(*) as n, round(avg(dist), 4) as mean from j where r <= 2 group by r_name
""")
def knn_by_region(spark, d):
    """Each customer's two orders nearest to a target price, summed up by region."""
    o, c, n, r = (table(spark, d, t) for t in ("orders", "customer", "nation", "region"))
    near = o.withColumn("dist", F.abs(F.col("o_totalprice") - 150000.0)).withColumn("k", F.row_number().over(Window.partitionBy("o_custkey").orderBy("dist", "o_orderkey"))).where("k <= 2")
    j = near.join(c, near.o_custkey == c.c_custkey).join(F.broadcast(n), F.col("c_nationkey") == n.n_nationkey).join(F.broadcast(r), F.col("n_regionkey") == r.r_regionkey)
    return j.groupBy("r_name").agg(F.count("*").alias("n"), F.round(F.avg("dist"), 4).alias("mean"))
