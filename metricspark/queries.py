"""The registered queries of the similarity engine, each with its brute-force SQL twin where SQL has one."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from . import relational
from .functions import metrics, sql as sql_surface
from .functions.metrics import UNROLLED
from .operators import baselines, global_index, index, intermediate, search, updates, variants
from .operators.sampling import distance_stats
from .operators.sizes import sized
from .plans import costmodel, measures, workloads
from .sources import datasource
from .sources.tables import LETTERS, SETS, frozen_queries, letters_of, load, table, written
from .streaming import streams

QUERIES: dict = {}
ORACLES: dict = {}
_built: dict = {}


def _kept(spark: SparkSession, key: tuple, make):
    """One result per session and arguments: queries over one set share its index, as a user's would."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _built:
        _built[key] = make()
    return _built[key]


def objects(spark, d: str, name: str) -> DataFrame:
    return _kept(spark, ("objects", d, name), lambda: written(load(spark, d, name), f"objects-{name}"))


def asked(spark, d: str, name: str) -> DataFrame:
    return _kept(spark, ("asked", d, name), lambda: written(frozen_queries(spark, d, name), f"asked-{name}"))


def the_index(spark, d: str, name: str, **options) -> index.MetricIndex:
    def make():
        objs, s = objects(spark, d, name), SETS[name]
        n_p = options.pop("n_p", None) or max(8, min(200, objs.count() // 50))
        return index.build_index(objs, s.metric, s.dim, n_p=n_p, **options)

    return _kept(spark, ("index", d, name, *sorted(options.items())), make)


# ---- SQL of the object sets and of brute force ----

SQL_SETS = {
    "event_points": "select event_id as oid, [(epoch_us(ts) - 1704067200000000) / 2592000000000.0::double, value / 100] as obj from events where ts is not null and value is not null",
    "order_points": "select o_orderkey as oid, [o_totalprice / 500000, date_diff('day', date '1995-01-01', o_orderdate::date) / 2500.0::double] as obj from orders",
    "embed": "select vec_id as oid, embedding::double[] as obj from embeddings",
    "letters_l1": f"select doc_id as oid, list_transform({list(LETTERS)}, lambda c: (length(lower(text)) - length(replace(lower(text), c, ''))) / length(text)) as obj from documents where length(text) > 0",
    "words": r"select distinct t as obj from (select unnest(regexp_split_to_array(lower(text), '\s+')) as t from documents) where regexp_full_match(t, '[a-z]{1,34}')",
    "line_vectors": "select l_orderkey, l_partkey, l_suppkey, l_linenumber, [l_quantity / 50, l_extendedprice / 105000, l_discount * 10, l_tax * 12.5, date_diff('day', date '1995-01-01', l_shipdate::date) / 2500.0::double] as obj from lineitem",
    "urls": "select page_id as oid, url as obj from pages where url is not null",
    "part_names": "select p_partkey as oid, p_name as obj from part where p_name is not null",
}
ASKED = "oid % 50 = 0"


def _base(name: str) -> str:
    key = "embed" if name.startswith("embed") else name
    return f"with o as ({SQL_SETS[key]}), q as (select * from o where {ASKED})"


def _d(name: str) -> str:
    return SETS[name].metric.sql("q.obj", "o.obj")


def sql_range(name: str, r: float | None = None) -> str:
    r = SETS[name].r if r is None else r
    return f"{_base(name)}, j as (select q.oid as qid, o.oid, {_d(name)} as d from o cross join q) select qid, oid, round(d, 6) as dist from j where d <= {r}"


def sql_knn(name: str, k: int = 8) -> str:
    return f"{_base(name)}, j as (select q.oid as qid, o.oid, {_d(name)} as d from o cross join q), r as (select *, row_number() over (partition by qid order by round(d, 9), oid) as rank from j) select qid, rank::integer as rank, oid, round(d, 6) as dist from r where rank <= {k}"


def ranged(df: DataFrame) -> DataFrame:
    return df.select("qid", "oid", F.round("dist", 6).alias("dist"))


def nearest(df: DataFrame) -> DataFrame:
    return df.select("qid", "rank", "oid", F.round("dist", 6).alias("dist"))


def query(sql: str | None = None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return keep


# ---- metrics ----


def _pairs_sql(metric: metrics.Metric, name: str) -> str:
    return f"{_base(name)} select o.oid, round(min({metric.sql('q.obj', 'o.obj')}), 6) as nearest, round(max({metric.sql('q.obj', 'o.obj')}), 6) as farthest from q cross join o group by o.oid"


def _pairs(metric: metrics.Metric, name: str):
    """The least and greatest distance of every object to all queries; one row an object goes on. All pairs are measured, but for short vectors, where bounds decide far and near runs of them."""

    def run(spark, d):
        o, q = objects(spark, d, name), asked(spark, d, name)
        if metric.name == "edit":
            return search.edit_extremes_by_block(o, q).select("oid", *[F.round(c, 6).alias(c) for c in ("nearest", "farthest")])
        if metric.crossed and (SETS[name].dim or UNROLLED + 1) <= UNROLLED:
            return search.extremes_by_block(o, metric, q).select("oid", *[F.round(c, 6).alias(c) for c in ("nearest", "farthest")])
        measure, root = metric.before_root or (metric.column, lambda x: x)
        pairs = o.crossJoin(sized(q)).select("oid", measure(F.col("q"), F.col("obj"), SETS[name].dim).alias("d"))
        return pairs.groupBy("oid").agg(F.round(root(F.min("d")), 6).alias("nearest"), F.round(root(F.max("d")), 6).alias("farthest"))

    return run


for _name, _metric, _set in (("dist_l1", metrics.l1(), "embed_l1"), ("dist_l2", metrics.l2(), "embed_l2"), ("dist_l3", metrics.lp(3), "event_points"), ("dist_linf", metrics.linf(), "embed_l2"), ("dist_edit", metrics.edit(), "urls")):
    query(_pairs_sql(_metric, _set), _name)(_pairs(_metric, _set))


@query("select * from (values ('identity', 1600::bigint, 0::bigint), ('non_negativity', 1600, 0), ('symmetry', 1600, 0), ('triangle', 64000, 0)) t(axiom, tested, violated)")
def axiom_violations(spark, d):
    return metrics.check_axioms(objects(spark, d, "event_points"), metrics.l2(), 40, 7, 2)


@query(name="distance_stats")
def distance_statistics(spark, d):
    out = None
    for name in ("event_points", "order_points", "line_vectors", "letters_l1", "embed_l2"):
        s = SETS[name]
        part = distance_stats(objects(spark, d, name), s.metric, 150, 11, s.dim).select(F.lit(name).alias("objects"), "*")
        out = part if out is None else out.unionByName(part)
    return out


# ---- range and nearest-neighbour search on all object sets ----


def _mrq(name: str, **options):
    return lambda spark, d: ranged(search.range_query(the_index(spark, d, name, **options), asked(spark, d, name), SETS[name].r))


def _knn(name: str, k: int = 8, **options):
    return lambda spark, d: nearest(search.knn_query(the_index(spark, d, name, **options), asked(spark, d, name), k))


for _short, _set in (("points", "event_points"), ("orders", "order_points"), ("letters", "letters_l1"), ("embed_l2", "embed_l2"), ("embed_l1", "embed_l1"), ("urls", "urls"), ("part_names", "part_names")):
    query(sql_range(_set), f"mrq_{_short}")(_mrq(_set))
    query(sql_knn(_set), f"knn_{_short}")(_knn(_set))
for _k in (1, 2, 4, 16, 32):
    query(sql_knn("event_points", _k), f"knn_points_k{_k}")(_knn("event_points", _k))
for _r in (0.5, 10.0):
    query(f"{_base('event_points')} select q.oid as qid, count(o.oid) as n from q left join o on {_d('event_points')} <= {_r} group by q.oid", f"mrq_points_r{str(_r).replace('.', '_')}")(lambda spark, d, r=_r: search.range_count(the_index(spark, d, "event_points"), asked(spark, d, "event_points"), r))
for _r in (0.0, 0.01, 0.1):
    query(sql_range("event_points", _r), f"mrq_points_r{str(_r).replace('.', '_')}")(lambda spark, d, r=_r: ranged(search.range_query(the_index(spark, d, "event_points"), asked(spark, d, "event_points"), r)))

_WORDS = f"with o as ({SQL_SETS['words']}), q as (select obj from o where ('0x' || substr(md5(obj), 1, 7))::bigint % 50 = 0), j as (select q.obj as query_word, o.obj as word, levenshtein(q.obj, o.obj)::double as dist from o cross join q)"


def _as_words(spark, d, df: DataFrame) -> DataFrame:
    o = objects(spark, d, "words")
    q = asked(spark, d, "words").select(F.col("qid").alias("q_"), F.col("q").alias("query_word"))
    return df.join(o.select(F.col("oid").alias("o_"), F.col("obj").alias("word")), F.col("oid") == F.col("o_")).join(q, F.col("qid") == F.col("q_"))


@query(f"{_WORDS} select query_word, word, dist from j where dist <= 2")
def mrq_words(spark, d):
    return _as_words(spark, d, search.range_query(the_index(spark, d, "words"), asked(spark, d, "words"), 2.0)).select("query_word", "word", "dist")


@query(f"{_WORDS}, r as (select *, row_number() over (partition by query_word order by dist, word) as rank from j) select query_word, rank::integer as rank, word, dist from r where rank <= 8")
def knn_words(spark, d):
    return _as_words(spark, d, search.knn_query(the_index(spark, d, "words"), asked(spark, d, "words"), 8, by="obj")).select("query_word", "rank", "word", "dist")


_LINES = f"with o as ({SQL_SETS['line_vectors']}), q as (select * from o where l_orderkey % 50 = 0), j as (select q.l_orderkey as q_order, q.l_partkey as q_part, o.l_orderkey as o_order, o.l_partkey as o_part, o.l_linenumber as o_line, list_distance(q.obj, o.obj) as d, q.obj as qv, o.obj as ov from o cross join q)"


def _as_lines(spark, d, df: DataFrame) -> DataFrame:
    t = table(spark, d, "lineitem")
    k = t.select(F.xxhash64(*t.columns).alias("k_"), "l_orderkey", "l_partkey", "l_linenumber")
    q = k.select(F.col("k_").alias("qk_"), F.col("l_orderkey").alias("q_order"), F.col("l_partkey").alias("q_part")).where("q_order % 50 = 0")
    o = k.select("k_", F.col("l_orderkey").alias("o_order"), F.col("l_partkey").alias("o_part"), F.col("l_linenumber").alias("o_line"))
    return df.join(o, F.col("oid") == F.col("k_")).join(q, F.col("qid") == F.col("qk_"))


@query(f"{_LINES} select q_order, q_part, o_order, o_part, o_line, round(d, 6) as dist from j where d <= 0.3")
def mrq_lines(spark, d):
    return _as_lines(spark, d, search.range_query(the_index(spark, d, "line_vectors"), asked(spark, d, "line_vectors"), 0.3)).select("q_order", "q_part", "o_order", "o_part", "o_line", F.round("dist", 6).alias("dist"))


@query(f"{_LINES}, r as (select *, row_number() over (partition by q_order, q_part, qv order by round(d, 9), o_order, o_part, o_line) as rank from j) select q_order, q_part, rank::integer as rank, round(d, 6) as dist from r where rank <= 8")
def knn_lines(spark, d):
    return _as_lines(spark, d, search.knn_query(the_index(spark, d, "line_vectors"), asked(spark, d, "line_vectors"), 8)).select("q_order", "q_part", "rank", F.round("dist", 6).alias("dist"))


@query(f"{_base('event_points')} select q.oid as qid, count(o.oid) as n from q left join o on {_d('event_points')} <= 0.05 group by q.oid")
def mrq_count(spark, d):
    return search.range_count(the_index(spark, d, "event_points"), asked(spark, d, "event_points"), 0.05)


@query(f"{_base('embed_l2')} select q.oid as qid from q where exists (select 1 from o where o.oid <> q.oid and {_d('embed_l2')} <= 1.17)")
def mrq_semi(spark, d):
    return search.range_exists(the_index(spark, d, "embed_l2"), asked(spark, d, "embed_l2"), 1.17, other_than_self=True)


@query(f"{_base('embed_l2')} select q.oid as qid from q where not exists (select 1 from o where o.oid <> q.oid and {_d('embed_l2')} <= 1.17)")
def mrq_anti(spark, d):
    return search.range_anti(the_index(spark, d, "embed_l2"), asked(spark, d, "embed_l2"), 1.17, other_than_self=True)


@query(f"{_base('event_points')}, j as (select q.oid as qid, o.oid, {_d('event_points')} as d from o cross join q) select qid, oid from j where d <= 0.05")
def mrq_without_distances(spark, d):
    return search.range_query(the_index(spark, d, "event_points"), asked(spark, d, "event_points"), 0.05, with_dist=False).select("qid", "oid")


@query(f"{_base('event_points')}, j as (select q.oid as qid, o.oid, {_d('event_points')} as d from o cross join q) select qid, oid, round(d, 6) as dist from j where d <= 0.02 + (qid % 5) * 0.01")
def mrq_own_radius(spark, d):
    q = asked(spark, d, "event_points").withColumn("r", F.lit(0.02) + (F.col("qid") % 5) * F.lit(0.01))
    return ranged(search.range_query(the_index(spark, d, "event_points"), q))


@query(f"{_base('event_points')}, j as (select q.oid as qid, o.oid, {_d('event_points')} as d from o cross join q) select qid, oid, round(d, 6) as dist from j join events on oid = event_id where d <= 0.05 and event_type = 'error'")
def filter_attr_then_mrq(spark, d):
    e = table(spark, d, "events").where("event_type = 'error'").select(F.col("event_id").alias("e_"))
    idx = the_index(spark, d, "event_points")
    return ranged(search.range_query(idx.with_objects(idx.objects.join(e, F.col("oid") == F.col("e_"), "left_semi")), asked(spark, d, "event_points"), 0.05))


@query(sql_knn("event_points", 8))
def knn_via_range(spark, d):
    return nearest(search.knn_via_range(the_index(spark, d, "event_points"), asked(spark, d, "event_points"), 8))


query(sql_knn("embed_l2"), "knn_embed")(_knn("embed_l2"))


@query(f"with o as ({SQL_SETS['embed']}), j as (select q.oid as qid, o.oid, {_d('embed_l2')} as d from o cross join o q), r as (select *, row_number() over (partition by qid order by round(d, 9), oid) as rank from j) select qid, rank::integer as rank, oid, round(d, 6) as dist from r where rank <= 2")
def knn_join(spark, d):
    return nearest(search.knn_join(objects(spark, d, "embed_l2"), the_index(spark, d, "embed_l2"), 2))


@query(f"with o as ({SQL_SETS['letters_l1']}), j as (select q.oid, o.oid as oid2, {_d('letters_l1')} as d from o join o q on q.oid < o.oid) select oid, oid2, round(d, 6) as dist from j where d <= 0.01")
def range_join_letters(spark, d):
    return search.range_join(the_index(spark, d, "letters_l1"), 0.01).select("oid", "oid2", F.round("dist", 6).alias("dist"))


@query(f"with o as ({SQL_SETS['letters_l1']}), q as ({SQL_SETS['letters_l1'].replace('doc_id', 'item_id').replace('documents', 'benchmark')}), j as (select q.oid as qid, o.oid, {_d('letters_l1')} as d from o cross join q) select qid, oid, round(d, 6) as dist from j where d <= 0.1")
def mrq_benchmark_letters(spark, d):
    q = letters_of(table(spark, d, "benchmark"), "item_id", "text").select(F.col("oid").alias("qid"), F.col("obj").alias("q"))
    return ranged(search.range_query(the_index(spark, d, "letters_l1"), q, 0.1))


# ---- baselines and ablations ----

EP = "event_points"
for _short, _options in (("random", {"placement": "random"}), ("homogeneous", {"placement": "homogeneous"}), ("flat_local", {"local": "flat"}), ("vantage_local", {"local": "vantage"}), ("leaves_by_partitions", {"balance": "partitions"})):
    query(sql_range(EP), f"mrq_tristage_{_short}")(_mrq(EP, **_options))
    query(sql_knn(EP), f"knn_tristage_{_short}")(_knn(EP, **_options))


@query(sql_range(EP))
def scan_mrq(spark, d):
    return ranged(baselines.scan_range(objects(spark, d, EP), SETS[EP].metric, asked(spark, d, EP), 0.05, 2))


@query(sql_knn(EP))
def scan_knn(spark, d):
    return nearest(baselines.scan_knn(objects(spark, d, EP), SETS[EP].metric, asked(spark, d, EP), 8, 2))


def pivot_key(spark, d, name=EP):
    return _kept(spark, ("pivot_key", d, name), lambda: baselines.pivot_key_build(objects(spark, d, name), SETS[name].metric, dim=SETS[name].dim))


def layered_pivot(spark, d, name=EP):
    return _kept(spark, ("layered_pivot", d, name), lambda: baselines.layered_pivot_build(objects(spark, d, name), SETS[name].metric, dim=SETS[name].dim))


@query(sql_range(EP))
def mrq_pivot_key(spark, d):
    return ranged(baselines.pivot_key_range(pivot_key(spark, d), asked(spark, d, EP), 0.05))


@query(sql_knn(EP))
def knn_pivot_key(spark, d):
    return nearest(baselines.pivot_key_knn(pivot_key(spark, d), asked(spark, d, EP), 8))


@query(sql_range(EP))
def mrq_layered_pivot(spark, d):
    return ranged(baselines.layered_pivot_range(layered_pivot(spark, d), asked(spark, d, EP), 0.05))


@query(sql_knn(EP))
def knn_layered_pivot(spark, d):
    return nearest(baselines.layered_pivot_knn(layered_pivot(spark, d), asked(spark, d, EP), 8))


@query(sql_range("letters_l1"))
def mrq_letters_pivot_key(spark, d):
    return ranged(baselines.pivot_key_range(pivot_key(spark, d, "letters_l1"), asked(spark, d, "letters_l1"), 0.045))


@query(sql_range("letters_l1"))
def mrq_letters_layered_pivot(spark, d):
    return ranged(baselines.layered_pivot_range(layered_pivot(spark, d, "letters_l1"), asked(spark, d, "letters_l1"), 0.045))


@query(sql_range(EP))
def mrq_single_mtree(spark, d):
    return ranged(baselines.single_mtree(objects(spark, d, EP), SETS[EP].metric, asked(spark, d, EP), r=0.05))


@query(sql_knn(EP))
def knn_single_mtree(spark, d):
    return nearest(baselines.single_mtree(objects(spark, d, EP), SETS[EP].metric, asked(spark, d, EP), k=8))


@query()
def knn_graph_ann(spark, d):
    return nearest(baselines.graph_ann_knn(objects(spark, d, "embed_l2"), SETS["embed_l2"].metric, asked(spark, d, "embed_l2"), 8))


@query()
def recall_graph_ann(spark, d):
    return measures.recall(knn_graph_ann(spark, d), search.knn_query(the_index(spark, d, "embed_l2"), asked(spark, d, "embed_l2"), 8))


@query("select true as high")
def recall_graph_ann_high(spark, d):
    return recall_graph_ann(spark, d).select((F.col("recall") >= 0.9).alias("high"))


@query(sql_range(EP))
def grid_mrq_points(spark, d):
    return ranged(baselines.grid_range(objects(spark, d, EP), asked(spark, d, EP), 0.05))


@query(sql_knn(EP))
def knn_per_slot(spark, d):
    return nearest(baselines.per_slot_knn(the_index(spark, d, EP), asked(spark, d, EP), 8))


# ---- structure, balance, costs ----


@query("select * from (values ('has one partition'), ('within covering radius'), ('within local radius'), ('stored distance is right'), ('no object twice')) r(rule) cross join (select count(*) as tested, 0::bigint as violated from events where ts is not null and value is not null)")
def partition_invariants(spark, d):
    return global_index.verify(the_index(spark, d, EP))


@query("select count(*) as n from events where ts is not null and value is not null")
def scan_index_slots(spark, d):
    """The events that a read of all slots' files finds."""
    e = table(spark, d, "events").where("ts is not null and value is not null").select("event_id")
    return e.join(the_index(spark, d, EP).objects.select("oid"), F.col("event_id") == F.col("oid"), "left_semi").agg(F.count("*").alias("n"))


@query("select true as same")
def scan_index_slot(spark, d):
    """A pruned read of one slot's files has as many objects as the placement says."""
    idx = the_index(spark, d, EP)
    return idx.objects.where("slot = 3").agg(F.count("*").alias("a")).crossJoin(idx.placement.where("slot = 3").agg(F.coalesce(F.sum("n_objects"), F.lit(0)).alias("b"))).select((F.col("a") == F.col("b")).alias("same"))


@query("select count(*) as tested, 0::bigint as violated from events where ts is not null and value is not null")
def partition_nearest(spark, d):
    """Every object hangs under the nearest of the centres it could choose from, on every level; checked by all distances."""
    return global_index.verify_nearest(the_index(spark, d, EP)).agg(F.max("tested").alias("tested"), F.sum("violated").cast("long").alias("violated"))


@query("select true as even")
def placement_dealt_evenly(spark, d):
    idx = the_index(spark, d, EP, balance="partitions")
    b = idx.placement.groupBy("bucket", "slot").agg(F.count("*").alias("n"))
    per_slot = b.groupBy("slot").agg(F.count("*").alias("buckets")).agg((F.max("buckets") - F.min("buckets")).alias("s"))
    return b.agg((F.max("n") - F.min("n")).alias("p")).crossJoin(per_slot).select(((F.col("p") <= 1) & (F.col("s") <= 1)).alias("even"))


_OBJECTS = "(select count(*) from events where ts is not null and value is not null)"


def _answers(r: float) -> str:
    return f"{_base(EP)}, a as (select count(*) as answers from q join o on {_d(EP)} <= {r})"


@query(f"select (s.i)::integer as slot, {_OBJECTS} as of_all, true as even from range(10) s(i)")
def placement_balance(spark, d):
    """Per slot: the objects of all slots, and whether the slot has at most twice its share."""
    b = measures.placement_balance(the_index(spark, d, EP))
    total = b.agg(F.sum("n_objects").alias("of_all"))
    return b.crossJoin(total).select("slot", "of_all", (F.col("n_objects") <= 0.2 * F.col("of_all")).alias("even"))


def _counts(index, q, r):
    """What must hold for the counts of a search: nothing is tested twice or lost between stages, and answers are among what was reached."""
    p = measures.pruning(index, q, r)
    sums = p.select("stage", (F.col("distance_calls") >= F.col("survived")).alias("measured"), (F.col("filtered") + F.col("survived") > 0).alias("reached"))
    return sums


_STAGES = "select * from (values ('partitions', true, true), ('clusters', true, true), ('objects', true, true)) t(stage, measured, reached)"


@query(_STAGES)
def lemma_counts_points(spark, d):
    return _counts(the_index(spark, d, EP), asked(spark, d, EP), 0.05)


@query(_STAGES)
def lemma_counts_words(spark, d):
    return _counts(the_index(spark, d, "words"), asked(spark, d, "words"), 2.0)


@query("select true as accepted_unseen")
def lemma_counts_wide_radius(spark, d):
    """A radius far over the clusters' own, where whole clusters are accepted unseen."""
    return measures.pruning(the_index(spark, d, EP), asked(spark, d, EP), 1.0).where("stage = 'partitions'").select((F.col("validated") > 0).alias("accepted_unseen"))


@query(f"{_answers(0.05)} select answers, true as covered, 10::bigint as slots from a")
def slot_workload(spark, d):
    """The slots' answers together, and whether each slot reached at least what it answered."""
    w = measures.workload(the_index(spark, d, EP), asked(spark, d, EP), 0.05)
    return w.agg(F.sum("answers").alias("answers"), F.bool_and(F.col("verified") + F.col("validated") >= F.col("answers")).alias("covered"), F.count("*").alias("slots"))


@query("select true as even")
def slot_load_deviation(spark, d):
    """The deviation of the objects to verify over the slots is under their mean."""
    return measures.load_deviation(measures.workload(the_index(spark, d, EP), asked(spark, d, EP), 0.05)).select((F.col("variation") < 1).alias("even"))


@query(f"{_answers(0.05)} select (select count(*) from q) as n_queries, {_OBJECTS} as objects, answers <= {_OBJECTS} * (select count(*) from q) as pruned, true as fewer from a")
def stage_counts(spark, d):
    """Queries, objects, and whether stages shrink: far fewer objects are verified than a scan would."""
    c = measures.stage_counts(the_index(spark, d, EP), asked(spark, d, EP), 0.05)
    scan = F.col("n_queries") * F.col("objects")
    return c.select("n_queries", F.col("objects").cast("long").alias("objects"), (F.col("reached") <= scan).alias("pruned"), (F.col("verified") * 4 < scan).alias("fewer"))


@query(f"select {_OBJECTS} as objects, true as each_partition_once, true as nodes_fewer")
def index_rows(spark, d):
    r = measures.index_rows(the_index(spark, d, EP)).groupBy().pivot("part", ["global", "intermediate", "local_nodes", "objects"]).agg(F.first("n"))
    return r.select("objects", (F.col("intermediate") <= F.col("global")).alias("each_partition_once"), (F.col("local_nodes") < F.col("objects")).alias("nodes_fewer"))


@query()
def cost_model(spark, d):
    """The printed costs and condition for the default setting over a grid, with the solved N_p or the reason for none."""
    rows = []
    for name in ("event_points", "line_vectors", "embed_l2"):
        s = SETS[name]
        c = costmodel.setting_for(objects(spark, d, name), s.metric, s.r, objects(spark, d, name).count(), dim=s.dim)
        n_p, why = costmodel.solve_n_p(c)
        rows.append((name, float(c.lam), n_p, why))
    for lam in (0.005, 0.01, 0.02, 0.5):
        n_p, why = costmodel.solve_n_p(costmodel.Setting(1e7, 10, 20, 1, lam))
        rows.append((f"lambda={lam}", lam, n_p, why))
    return spark.createDataFrame(rows, "setting string, lambda double, n_p double, outcome string")


@query()
def choose_partitions(spark, d):
    """Counted costs of pilot indexes by N_p beside the printed model's, and their ratio."""
    o = objects(spark, d, EP)
    rows = costmodel.choose_n_p(o, metrics.l2(), 0.05, grid=(50, 100, 200), dim=2)
    setting = costmodel.setting_for(o, metrics.l2(), 0.05, o.count(), dim=2)
    counted = spark.createDataFrame([(r["n_p"], float(r["total"])) for r in rows], "n_p int, counted double")
    cost = lambda n_p: costmodel.total_cost(setting, n_p)
    # a survival rate under 0 has no real power: there the model says nothing
    predicted = spark.createDataFrame([(r["n_p"], None if isinstance(cost(r["n_p"]), complex) else float(cost(r["n_p"]))) for r in rows], "n_p int, predicted double")
    return measures.model_error(predicted, counted)


# ---- variants that place objects ----

_N_EVENTS = "select count(*) as n from events where ts is not null and value is not null"


@query(sql_range(EP))
def place_cluster_round_robin(spark, d):
    return ranged(variants.range_by_object(the_index(spark, d, EP), variants.cluster_id_round_robin, asked(spark, d, EP), 0.05))


@query(sql_range(EP))
def place_heterogeneous(spark, d):
    return ranged(variants.range_by_object(the_index(spark, d, EP), variants.heterogeneous_placement, asked(spark, d, EP), 0.05))


@query(sql_range(EP))
def place_replicated(spark, d):
    return ranged(variants.range_replicated(the_index(spark, d, EP), asked(spark, d, EP), 0.05, 2))


@query("select true as found")
def ordered_lookup(spark, d):
    idx = the_index(spark, d, EP)
    rows = idx.placement.collect()
    tree = intermediate.OrderedLeafIndex([(r.dist_to_parent, r.pid) for r in rows])
    ok = all(tree.lookup(r.pid) == tree.lookup_linear(r.pid) for r in rows)
    return spark.createDataFrame([(ok,)], "found boolean")


# ---- updates ----


def _edited(spark, d):
    def make():
        s = objects(spark, d, EP)
        base = index.build_index(s.where("oid % 10 <> 3"), metrics.l2(), 2, n_p=100)
        return updates.delete(updates.insert(base, s.where("oid % 10 = 3")), s.where("oid % 7 = 5").select("oid"))

    return _kept(spark, ("edited", d), make)


_EDITED = f"with o as (select * from ({SQL_SETS[EP]}) where oid % 7 <> 5), q as (select * from ({SQL_SETS[EP]}) where {ASKED}), j as (select q.oid as qid, o.oid, {_d(EP)} as d from o cross join q)"


@query(f"{_EDITED} select qid, oid, round(d, 6) as dist from j where d <= 0.05")
def mrq_after_updates(spark, d):
    return ranged(search.range_query(_edited(spark, d), asked(spark, d, EP), 0.05))


@query(f"{_EDITED}, r as (select *, row_number() over (partition by qid order by round(d, 9), oid) as rank from j) select qid, rank::integer as rank, oid, round(d, 6) as dist from r where rank <= 8")
def knn_after_updates(spark, d):
    return nearest(search.knn_query(_edited(spark, d), asked(spark, d, EP), 8))


@query(f"{_EDITED} select qid, oid, round(d, 6) as dist from j where d <= 0.05")
def mrq_after_compaction(spark, d):
    return ranged(search.range_query(updates.compact(_edited(spark, d)), asked(spark, d, EP), 0.05))


@query(sql_range(EP))
def mrq_reopened(spark, d):
    return ranged(search.range_query(index.open_index(spark, the_index(spark, d, EP).path), asked(spark, d, EP), 0.05))


# ---- sources and SQL surface ----


@query(_N_EVENTS)
def source_metric_index(spark, d):
    datasource.register(spark)
    return spark.read.format("metric_index").option("path", the_index(spark, d, EP).path.removeprefix("file://")).load().agg(F.count("*").alias("n"))


@query(sql_range(EP))
def sql_range_function(spark, d):
    sql_surface.register_functions(spark)
    sql_surface.register_index(spark, the_index(spark, d, EP), "ep")
    asked(spark, d, EP).createOrReplaceTempView("ep_asked")
    return ranged(spark.sql("select c.qid, o.oid, l2_distance(c.q, o.obj) as dist from (select q.qid, q.q, t.pid from ep_asked q, lateral ep_range(q.q, 0.05D) t) c join ep_objects o on o.pid = c.pid where l2_distance(c.q, o.obj) <= 0.05D"))


@query(sql_knn(EP))
def sql_knn_function(spark, d):
    sql_surface.register_functions(spark)
    sql_surface.register_index(spark, the_index(spark, d, EP), "ep")
    asked(spark, d, EP).createOrReplaceTempView("ep_asked")
    found = spark.sql("select c.qid, o.oid, l2_distance(c.q, o.obj) as dist, 8 as k from (select q.qid, q.q, t.pid from ep_asked q, lateral ep_knn(q.q, 8) t) c join ep_objects o on o.pid = c.pid")
    return nearest(search.rank_answers(found))


@query(f"{_base('embed_l2')}, one as (select obj from o where oid = 0) select o.oid, round(list_distance(o.obj, one.obj), 6) as dist from o cross join one")
def udf_distances(spark, d):
    """Distances to one object by a vectorised function over Arrow batches, for wide vectors."""
    o = objects(spark, d, "embed_l2")
    one = o.where("oid = 0").first().obj
    return o.select("oid", F.round(sql_surface.distance_udf(metrics.l2(), list(one))("obj"), 6).alias("dist"))


@query()
def distance_histogram(spark, d):
    return sql_surface.distance_histogram(objects(spark, d, EP), metrics.l2(), dim=2)


@query(f"{_base(EP)}, j as (select q.oid as qid, o.oid, {_d(EP)} as d from o cross join q), r as (select *, row_number() over (partition by qid order by round(d, 9), oid) as rank from j) select qid, rank::integer as rank, oid, round(d, 6) as dist from r where rank <= 4")
def agg_bounded_top_k(spark, d):
    """The k nearest as an aggregate: bounded arrays a task, merged."""
    return nearest(sql_surface.top_k_aggregate(objects(spark, d, EP), metrics.l2(), asked(spark, d, EP), 4, 2))


@query()
def local_medoids(spark, d):
    return sql_surface.medoids(the_index(spark, d, EP).objects, metrics.l2())


# ---- streams: the end of each equals a batch query ----


@query(sql_range(EP))
def stream_equiv_standing(spark, d):
    found = streams.standing_queries(streams.event_stream(spark, d), asked(spark, d, EP), metrics.l2(), 0.05, 2)
    return ranged(streams.run_to_end(found, "standing"))


@query(sql_range(EP))
def stream_equiv_inserts(spark, d):
    start = index.build_index(objects(spark, d, EP).limit(0), metrics.l2(), 2, n_p=100)
    return ranged(search.range_query(streams.continuous_inserts(streams.event_stream(spark, d), start), asked(spark, d, EP), 0.05))


@query("select date_trunc('day', ts)::timestamp as w_start, event_type, count(*) as n, round(sum(value), 4) as total from events group by 1, 2")
def stream_equiv_tumbling(spark, d):
    return streams.run_to_end(streams.tumbling(streams.event_stream(spark, d)), "tumbling", "complete").select(F.col("w_start").cast("timestamp_ntz").alias("w_start"), "event_type", "n", "total")


@query("select a.event_id as click, b.event_id as purchase from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 60 minutes and abs(a.value - b.value) <= 10")
def stream_equiv_join(spark, d):
    return streams.run_to_end(streams.purchases_after_clicks(streams.event_stream(spark, d)), "click_purchase")


@query("select count(*) as n from events")
def stream_equiv_dedup(spark, d):
    e = streams.event_stream(spark, d)
    return streams.run_to_end(streams.deduplicated(e.unionByName(streams.event_stream(spark, d))), "dedup").agg(F.count("*").alias("n"))


# ---- experiments: whole tables, the sets and grids named here ----

_W = workloads
_E = (EP,)
for _label, _f in {
    "w01_construction": lambda s, d: _W.construction(s, d, _E),
    "w02_build_by_workers": lambda s, d: _W.build_by_workers(s, d, _E),
    "w03_build_by_partitions": lambda s, d: _W.build_by_partitions(s, d, _E),
    "w04_update_cycle": lambda s, d: _W.update_cycle(s, d, _E),
    "w05_growth": lambda s, d: _W.growth(s, d, ("embed_l2",)),
    "w06_radius_sweep": lambda s, d: _W.radius_sweep(s, d, _E, ("tristage", "pivot_key", "layered_pivot", "single_mtree")),
    "w07_k_sweep": lambda s, d: _W.k_sweep(s, d, _E, ("tristage", "pivot_key", "layered_pivot", "single_mtree", "graph_ann")),
    "w08_tree_fanout_sweep": lambda s, d: _W.tree_fanout_sweep(s, d, _E),
    "w09_leaf_fanout_sweep": lambda s, d: _W.leaf_fanout_sweep(s, d, _E),
    "w10_partition_sweep": lambda s, d: _W.partition_sweep(s, d, _E),
    "w11_worker_sweep": lambda s, d: _W.worker_sweep(s, d, ("letters_l1",), values=(2, 6, 10)),
    "w12_cardinality_sweep": lambda s, d: _W.cardinality_sweep(s, d, _E, ("tristage", "pivot_key")),
    "w13_motivating_imbalance": lambda s, d: _W.motivating_imbalance(s, d),
    "w14_hot_spot": lambda s, d: _W.hot_spot(s, d, ("order_points",)),
    "w15_lookup_ablation": lambda s, d: _W.lookup_ablation(s, d),
}.items():
    query(None, _label)(_f)


@query("""
    select 'worked_examples' as workload, objects, 'tristage' as method, parameter, value::double as value, 'distance' as measure, round(result, 9) as result from (values
        ('strings', 'range_1', 1, 1.0::double), ('strings', 'range_1', 3, 1), ('strings', 'knn_3', 1, 1), ('strings', 'knn_3', 3, 1), ('strings', 'knn_3', 0, 2),
        ('points', 'range_2sqrt2', 8, sqrt(2)), ('points', 'range_2sqrt2', 9, 0), ('points', 'range_2sqrt2', 10, sqrt(2)), ('points', 'range_2sqrt2', 11, sqrt(8)), ('points', 'range_2sqrt2', 13, 1),
        ('points', 'knn_2', 9, 0), ('points', 'knn_2', 13, 1)) t(objects, parameter, value, result)
""")
def w16_worked_examples(spark, d):
    return workloads.worked_examples(spark).withColumn("result", F.round("result", 9))


QUERIES |= relational.QUERIES
ORACLES |= relational.ORACLES
