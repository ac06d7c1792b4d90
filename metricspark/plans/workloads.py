"""The experiments as functions: each takes (spark, sf_dir, ...) and gives [workload, objects, method, parameter, value, measure, result]."""
from __future__ import annotations

from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..operators import baselines, search, updates, variants
from ..operators.index import MetricIndex, build_index
from ..operators.intermediate import OrderedLeafIndex
from ..operators.sampling import hash_sample, radius_for, share
from ..sources.tables import SETS, load, written
from . import measures

SCHEMA = "workload string, objects string, method string, parameter string, value double, measure string, result double"
RADII, KS, FANOUTS, PARTITIONS, WORKERS, CARDINALITIES, GROWTH = (0.1, 0.2, 0.4, 0.8, 1.6, 3.2), (1, 2, 4, 8, 16, 32), (5, 10, 20, 40, 80), (50, 100, 200, 400, 800, 1600), (2, 4, 6, 8, 10), (20, 40, 60, 80, 100), (2, 4, 6, 8, 10)
DEFAULT = {"n_p": 200, "n_w": 10, "fanout": 20, "k": 8, "percent": 0.8}
TREE_METHODS = {"tristage": {}, "tristage_random": {"placement": "random"}, "tristage_flat_local": {"local": "flat"}, "tristage_vantage_local": {"local": "vantage"}}
EXACT = (*TREE_METHODS, "pivot_key", "layered_pivot")


def _objects(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return written(load(spark, sf_dir, name), f"objects-{name}")


def _queries(objects: DataFrame, n: int, seed: int) -> DataFrame:
    return written(hash_sample(objects, n, seed).select(F.col("oid").alias("qid"), F.col("obj").alias("q")), "queries")


def _tree(objects: DataFrame, name: str, method: str = "tristage", **options) -> MetricIndex:
    s = SETS[name]
    given = {"n_p": DEFAULT["n_p"], "n_w": DEFAULT["n_w"], "fanout": DEFAULT["fanout"]} | TREE_METHODS[method] | options
    return build_index(objects, s.metric, s.dim, **given)


def _method(objects: DataFrame, name: str, method: str, **options):
    """(build result, range(queries, r), knn(queries, k)) of a method."""
    s = SETS[name]
    if method in TREE_METHODS:
        idx = _tree(objects, name, method, **options)
        return idx, lambda q, r: search.range_query(idx, q, r), lambda q, k: search.knn_query(idx, q, k)
    n_w = options.get("n_w", DEFAULT["n_w"])
    if method == "pivot_key":
        pk = baselines.pivot_key_build(objects, s.metric, dim=s.dim, n_w=n_w)
        return pk, lambda q, r: baselines.pivot_key_range(pk, q, r), lambda q, k: baselines.pivot_key_knn(pk, q, k)
    if method == "layered_pivot":
        lp = baselines.layered_pivot_build(objects, s.metric, dim=s.dim, n_w=n_w)
        return lp, lambda q, r: baselines.layered_pivot_range(lp, q, r), lambda q, k: baselines.layered_pivot_knn(lp, q, k)
    if method == "single_mtree":
        _run(baselines.single_mtree(objects, s.metric, objects.select(F.col("oid").alias("qid"), F.col("obj").alias("q")).limit(0), k=1))  # the build alone
        return None, lambda q, r: baselines.single_mtree(objects, s.metric, q, r=r), lambda q, k: baselines.single_mtree(objects, s.metric, q, k=k)
    if method == "graph_ann":
        _run(baselines.graph_ann_knn(objects, s.metric, objects.select(F.col("oid").alias("qid"), F.col("obj").alias("q")).limit(0), 1, n_w=n_w))
        return None, baselines.graph_ann_range, lambda q, k: baselines.graph_ann_knn(objects, s.metric, q, k, n_w=n_w)
    if method == "scan":
        return None, lambda q, r: baselines.scan_range(objects, s.metric, q, r, s.dim), lambda q, k: baselines.scan_knn(objects, s.metric, q, k, s.dim)
    raise KeyError(method)


def _run(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def _bytes(spark, built) -> int | None:
    """Bytes of a method's files; one tree in a task and the graphs of the workers are never stored."""
    if isinstance(built, MetricIndex):
        return measures.index_bytes(spark, built.path)
    return measures.index_bytes(spark, built.objects._written_at) if built is not None else None


def _frame(spark, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame([(w, o, m, p, float(v), ms, None if x is None else float(x)) for w, o, m, p, v, ms, x in rows], SCHEMA)


def construction(spark, sf_dir, objects: Iterable[str] = ("event_points", "letters_l1"), methods: Iterable[str] = (*EXACT, "single_mtree", "graph_ann"), n_queries: int = 100, seed: int = 1) -> DataFrame:
    rows = []
    for name in objects:
        objs = _objects(spark, sf_dir, name)
        for method in methods:
            built, s = measures.timed(lambda: _method(objs, name, method)[0])
            rows.append(("construction", name, method, "-", 0, "seconds", s))
            rows.append(("construction", name, method, "-", 0, "bytes", _bytes(spark, built)))
    return _frame(spark, rows)


def _build_sweep(spark, sf_dir, objects, methods, label, parameter, values) -> DataFrame:
    rows = []
    for name in objects:
        objs = _objects(spark, sf_dir, name)
        for method in methods:
            took = {}
            for v in values:
                idx, s = measures.timed_build(lambda: _tree(objs, name, method, **{parameter: v}))
                rows += [(label, name, method, parameter, v, "seconds", s), (label, name, method, parameter, v, "bytes", measures.index_bytes(spark, idx.path)), (label, name, method, parameter, v, "partitions", idx.placement.count())]
                took[v] = s
                b = measures.placement_balance(idx).agg(F.stddev_pop("n_objects")).first()[0]
                rows.append((label, name, method, parameter, v, "balance_stddev", b))
            if parameter == "n_w":
                rows += [(label, name, method, parameter, v, "speedup", x) for v, x in measures.speedup(took).items()]
    return _frame(spark, rows)


def build_by_workers(spark, sf_dir, objects=("event_points", "letters_l1"), methods=("tristage",), n_queries=100, seed=1, values=WORKERS) -> DataFrame:
    return _build_sweep(spark, sf_dir, objects, methods, "build_by_workers", "n_w", values)


def build_by_partitions(spark, sf_dir, objects=("words", "event_points", "embed_l2", "letters_l1"), methods=("tristage",), n_queries=100, seed=1, values=PARTITIONS) -> DataFrame:
    return _build_sweep(spark, sf_dir, objects, methods, "build_by_partitions", "n_p", values)


def update_cycle(spark, sf_dir, objects=("event_points",), methods=("tristage",), n_queries=100, seed=1, n: int = 1000, n_single: int = 2) -> DataFrame:
    """Delete `n` random objects and put them back; range search before and after. Updates go in one batch each way; `n_single`
    objects are deleted and put back one after the other, each change a batch of its own, whose cost is that of Spark jobs."""
    rows = []
    for name in objects:
        objs, s = _objects(spark, sf_dir, name), SETS[name]
        q = _queries(objs, n_queries, seed)
        idx = _tree(objs, name)
        before = measures.query_time(lambda: search.range_query(idx, q, s.r), n_queries)
        some = written(hash_sample(objs, n, seed + 5), "moved")
        edited, secs = measures.timed(lambda: updates.insert(updates.delete(idx, some.select("oid")), some))
        after = measures.query_time(lambda: search.range_query(edited, q, s.r), n_queries)

        def one_by_one():
            now = idx
            for r in some.orderBy("oid").limit(n_single).collect():
                single = spark.createDataFrame([r], some.schema)
                now = updates.insert(updates.delete(now, single.select("oid")), single)
            return now

        rows.append(("update_cycle", name, "tristage", "n", n_single, "ms_per_single_update", measures.update_cost(measures.timed(one_by_one)[1], n_single)))
        same = search.range_query(idx, q, s.r).select("qid", "oid").exceptAll(search.range_query(edited, q, s.r).select("qid", "oid")).count()
        rows += [("update_cycle", name, "tristage", "n", n, "ms_per_update", measures.update_cost(secs, n)), ("update_cycle", name, "tristage", "n", n, "seconds_before", before), ("update_cycle", name, "tristage", "n", n, "seconds_after", after), ("update_cycle", name, "tristage", "n", n, "answers_lost", same)]
    return _frame(spark, rows)


def growth(spark, sf_dir, objects=("embed_l2", "letters_l1"), methods=("tristage", "pivot_key", "layered_pivot"), n_queries=100, seed=1, values=GROWTH) -> DataFrame:
    """Objects added in steps of a few percent; the pivot indexes are built anew, ours is extended."""
    rows = []
    for name in objects:
        objs, s = _objects(spark, sf_dir, name), SETS[name]
        base = share(objs, 100 - max(values))
        q = _queries(base, n_queries, seed)
        idx = _tree(base, name) if "tristage" in methods else None
        for v in values:
            grown = share(objs, 100 - max(values) + v)
            more = grown.join(base.select(F.col("oid").alias("b_")), F.col("oid") == F.col("b_"), "left_anti")
            for method in methods:
                if method == "tristage":
                    now = updates.insert(idx, more)
                    answer = lambda: search.range_query(now, q, s.r)
                else:
                    r = _method(grown, name, method)[1]
                    answer = lambda: r(q, s.r)
                rows.append(("growth", name, method, "percent", v, "seconds_per_query", measures.query_time(answer, n_queries)))
    return _frame(spark, rows)


def _query_sweep(spark, sf_dir, objects, methods, n_queries, seed, label, parameter, values, kind: str) -> DataFrame:
    rows = []
    for name in objects:
        objs, s = _objects(spark, sf_dir, name), SETS[name]
        q = _queries(objs, n_queries, seed)
        for method in methods:
            built, rng, knn = _method(objs, name, method)
            for v in values:
                if kind == "range":
                    r = radius_for(objs, s.metric, v, dim=s.dim)
                    if method == "graph_ann":
                        continue
                    rows.append((label, name, method, parameter, v, "seconds_per_query", measures.query_time(lambda: rng(q, r), n_queries)))
                    rows += [(label, name, method, parameter, v, m, x) for m, x in _search_counts(built, q, r)]
                else:
                    rows.append((label, name, method, parameter, v, "seconds_per_query", measures.query_time(lambda: knn(q, int(v)), n_queries)))
    return _frame(spark, rows)


def _search_counts(built, q, r) -> list[tuple[str, float]]:
    """Objects whose distance is computed, and (query, partition) pairs sent on, where the method has such."""
    if isinstance(built, MetricIndex):
        c = measures.stage_counts(built, q, r).first()
        return [("verified", c.verified), ("shipped", c.candidate_partitions)]
    candidates = {baselines.PivotKeyIndex: baselines.pivot_key_candidates, baselines.LayeredPivotIndex: baselines.layered_pivot_candidates}.get(type(built))
    return [("verified", candidates(built, search.with_radius(q, r)).count())] if candidates else []


def radius_sweep(spark, sf_dir, objects=("words", "event_points", "embed_l2", "letters_l1"), methods=EXACT, n_queries=100, seed=1, values=RADII) -> DataFrame:
    return _query_sweep(spark, sf_dir, objects, methods, n_queries, seed, "radius_sweep", "percent", values, "range")


def k_sweep(spark, sf_dir, objects=("words", "event_points", "embed_l2", "letters_l1"), methods=(*EXACT, "graph_ann"), n_queries=100, seed=1, values=KS) -> DataFrame:
    return _query_sweep(spark, sf_dir, objects, methods, n_queries, seed, "k_sweep", "k", values, "knn")


def _index_sweep(spark, sf_dir, objects, n_queries, seed, label, parameter, values, option, knn: bool = False, methods=("tristage",)) -> DataFrame:
    rows = []
    for name in objects:
        objs, s = _objects(spark, sf_dir, name), SETS[name]
        q = _queries(objs, n_queries, seed)
        for method in methods:
            for v in values:
                built, rng, nn = _method(objs, name, method, **option(v))
                rows.append((label, name, method, parameter, v, "seconds_per_query", measures.query_time(lambda: rng(q, s.r), n_queries)))
                if knn:
                    rows.append((label, name, method, parameter, v, "knn_seconds_per_query", measures.query_time(lambda: nn(q, DEFAULT["k"]), n_queries)))
                if isinstance(built, MetricIndex):
                    c = measures.stage_counts(built, q, s.r).first()
                    d = measures.load_deviation(measures.workload(built, q, s.r)).first()
                    rows += [(label, name, method, parameter, v, m, x) for m, x in (("verified", c.verified), ("shipped", c.candidate_partitions), ("buckets", built.placement.select("bucket").distinct().count()), ("load_stddev", d.stddev), ("load_variation", d.variation))]
    return _frame(spark, rows)


def tree_fanout_sweep(spark, sf_dir, objects=("event_points", "letters_l1"), methods=("tristage",), n_queries=100, seed=1, values=FANOUTS) -> DataFrame:
    return _index_sweep(spark, sf_dir, objects, n_queries, seed, "tree_fanout_sweep", "fanout", values, lambda v: {"fanout": v})


def leaf_fanout_sweep(spark, sf_dir, objects=("event_points", "letters_l1"), methods=("tristage",), n_queries=100, seed=1, values=FANOUTS) -> DataFrame:
    return _index_sweep(spark, sf_dir, objects, n_queries, seed, "leaf_fanout_sweep", "leaf_capacity", values, lambda v: {"leaf_capacity": v})


def partition_sweep(spark, sf_dir, objects=("event_points", "embed_l2"), methods=("tristage",), n_queries=100, seed=1, values=PARTITIONS) -> DataFrame:
    return _index_sweep(spark, sf_dir, objects, n_queries, seed, "partition_sweep", "n_p", values, lambda v: {"n_p": v}, knn=True)


def worker_sweep(spark, sf_dir, objects=("words", "letters_l1"), methods=("tristage", "tristage_random", "pivot_key", "layered_pivot"), n_queries=100, seed=1, values=WORKERS) -> DataFrame:
    """Time, and mean, deviation and variation of the workers' loads (objects to verify), for our index and the pivot baselines."""
    rows = []
    for name in objects:
        objs, s = _objects(spark, sf_dir, name), SETS[name]
        q = _queries(objs, n_queries, seed)
        for method in methods:
            took = {}
            for v in values:
                built, rng, _ = _method(objs, name, method, n_w=v)
                took[v] = measures.query_time(lambda: rng(q, s.r), n_queries)
                rows.append(("worker_sweep", name, method, "n_w", v, "seconds_per_query", took[v]))
                rows += [("worker_sweep", name, method, "n_w", v, m, x) for m, x in _spread(_load(built, q, s.r, v))]
            rows += [("worker_sweep", name, method, "n_w", v, "speedup", x) for v, x in measures.speedup(took).items()]
    return _frame(spark, rows)


def cardinality_sweep(spark, sf_dir, objects=("words", "event_points", "embed_l2", "letters_l1", "line_vectors"), methods=("tristage",), n_queries=100, seed=1, values=CARDINALITIES) -> DataFrame:
    rows = []
    for name in objects:
        objs, s = _objects(spark, sf_dir, name), SETS[name]
        for v in values:
            part = written(share(objs, v), "share")
            q = _queries(part, n_queries, seed)
            for method in methods:
                _, rng, knn = _method(part, name, method)
                rows += [("cardinality_sweep", name, method, "percent", v, "range_per_minute", measures.throughput(lambda: rng(q, s.r), n_queries)), ("cardinality_sweep", name, method, "percent", v, "knn_per_minute", measures.throughput(lambda: knn(q, DEFAULT["k"]), n_queries))]
    return _frame(spark, rows)


def _load(built, q, r: float, n_w: int) -> list[float]:
    """Objects to verify per worker. Ranges of keys, and boxes by number, are the workers of the pivot baselines."""
    if isinstance(built, MetricIndex):
        return [x.verified + x.validated for x in measures.workload(built, q, r).collect()]  # one row a worker
    if isinstance(built, baselines.LayeredPivotIndex):
        of = baselines.layered_pivot_candidates(built, search.with_radius(q, r)).select(F.pmod("box", F.lit(n_w)).alias("w"))
    else:
        cuts = built.objects.select(F.percentile_approx("key", [i / n_w for i in range(1, n_w)], 10000).alias("c")).first().c or []
        where = F.lit(0)
        for c in cuts:
            where = where + (F.col("key") > F.lit(float(c))).cast("int")
        cand = baselines.pivot_key_candidates(built, search.with_radius(q, r)).select(F.col("oid").alias("o_"))
        of = cand.join(built.objects.select("oid", where.alias("w")), F.col("o_") == F.col("oid"))
    got = {x.w: x.n for x in of.groupBy("w").agg(F.count("*").alias("n")).collect()}
    return [got.get(w, 0) for w in range(n_w)]


def _loads(objs, name, q, n_w) -> dict[str, list[float]]:
    """Objects to verify per worker, by method."""
    s, out = SETS[name], {}
    for method, options in (("tristage", {}), ("tristage_random", {"placement": "random"}), ("homogeneous", {"placement": "homogeneous"})):
        out[method] = _load(build_index(objs, s.metric, s.dim, n_p=DEFAULT["n_p"], n_w=n_w, **options), q, s.r, n_w)
    out["pivot_key"] = _load(baselines.pivot_key_build(objs, s.metric, dim=s.dim, n_w=n_w), q, s.r, n_w)
    out["layered_pivot"] = _load(baselines.layered_pivot_build(objs, s.metric, dim=s.dim, n_w=n_w), q, s.r, n_w)
    return out


def _spread(xs: list[float]) -> list[tuple[str, float | None]]:
    mean = sum(xs) / len(xs)
    sd = (sum((x - mean) ** 2 for x in xs) / len(xs)) ** 0.5
    return [("load_mean", mean), ("load_stddev", sd), ("load_variation", sd / mean if mean else None)]


def _imbalance(spark, label, name, loads) -> DataFrame:
    rows = []
    for method, xs in loads.items():
        rows += [(label, name, method, "n_w", len(xs), m, v) for m, v in (("most", max(xs)), ("least", min(xs)), *_spread(xs))]
    return _frame(spark, rows)


def motivating_imbalance(spark, sf_dir, objects=("event_points",), methods=(), n_queries=100, seed=1, n_w: int = 10) -> DataFrame:
    out = None
    for name in objects:
        objs = _objects(spark, sf_dir, name)
        part = _imbalance(spark, "motivating_imbalance", name, _loads(objs, name, _queries(objs, n_queries, seed), n_w))
        out = part if out is None else out.unionByName(part)
    return out


def hot_spot(spark, sf_dir, objects=("event_points", "order_points"), methods=(), n_queries=100, seed=1, n_w: int = 10) -> DataFrame:
    """Queries are the nearest neighbours of one object."""
    out = None
    for name in objects:
        objs, s = _objects(spark, sf_dir, name), SETS[name]
        one = _queries(objs, 1, seed)
        near = baselines.scan_knn(objs, s.metric, one, n_queries, s.dim).select(F.col("oid").alias("n_"))
        q = written(objs.join(near, F.col("oid") == F.col("n_")).select(F.col("oid").alias("qid"), F.col("obj").alias("q")), "hot")
        part = _imbalance(spark, "hot_spot", name, _loads(objs, name, q, n_w))
        out = part if out is None else out.unionByName(part)
    return out


def lookup_ablation(spark, sf_dir, objects=("event_points",), methods=(), n_queries=100, seed=1, values=PARTITIONS) -> DataFrame:
    """Comparisons of lookups in the ordered index against reading all entries."""
    rows = []
    for name in objects:
        idx = _tree(_objects(spark, sf_dir, name), name, n_p=max(values))
        entries = [(r.dist_to_parent, r.pid) for r in idx.placement.collect()]
        for v in values:
            some = sorted(entries, key=lambda e: (e[1] * 2654435761 % (1 << 32), e[1]))[:v]
            for method in ("ordered", "linear"):
                index = OrderedLeafIndex(some, DEFAULT["fanout"])
                for _, pid in some:
                    index.lookup(pid) if method == "ordered" else index.lookup_linear(pid)
                rows.append(("lookup_ablation", name, method, "n_p", v, "comparisons", index.comparisons / max(1, len(some))))
    return _frame(spark, rows)


LATTICE = {1: (-6, 1), 2: (-4, 0), 3: (4, 4), 4: (-5, 1), 5: (5, 4), 6: (4, 3), 7: (-3, 1), 8: (0, 0), 9: (1, 1), 10: (0, 2), 11: (3, 3), 12: (-6, 2), 13: (1, 0)}  # fixed values: the thirteen points of FIXTURES.md


def worked_examples(spark, sf_dir=None, objects=(), methods=(), n_queries=1, seed=1) -> DataFrame:
    """Answers of the worked examples: four strings under edit distance, thirteen points under L2."""
    from ..functions.metrics import edit, l2

    words = spark.createDataFrame(list(enumerate(["00100", "10111", "01001", "0110"])), "oid long, obj string")
    q = spark.createDataFrame([(0, "10110")], "qid long, q string")
    points = spark.createDataFrame([(i, [float(x), float(y)]) for i, (x, y) in LATTICE.items()], "oid long, obj array<double>")
    p9 = points.where("oid = 9").select(F.col("oid").alias("qid"), F.col("obj").alias("q"))
    wi = build_index(words, edit(), None, n_p=2, n_w=2, fanout=2)
    pi = build_index(points, l2(), 2, n_p=6, n_w=2, fanout=3)
    rows = []
    for label, df in (("range_1", search.range_query(wi, q, 1.0)), ("knn_3", search.knn_query(wi, q, 3))):
        rows += [("worked_examples", "strings", "tristage", label, r.oid, "distance", r.dist) for r in df.collect()]
    for label, df in (("range_2sqrt2", search.range_query(pi, p9, 8.0**0.5 + 1e-9)), ("knn_2", search.knn_query(pi, p9, 2))):
        rows += [("worked_examples", "points", "tristage", label, r.oid, "distance", r.dist) for r in df.collect()]
    return _frame(spark, rows)


ALL: dict[str, Callable[..., DataFrame]] = {f.__name__: f for f in (construction, build_by_workers, build_by_partitions, update_cycle, growth, radius_sweep, k_sweep, tree_fanout_sweep, leaf_fanout_sweep, partition_sweep, worker_sweep, cardinality_sweep, motivating_imbalance, hot_spot, lookup_ablation, worked_examples)}
__all__ = ["ALL", "variants"]
