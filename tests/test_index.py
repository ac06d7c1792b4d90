from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from metricspark.functions import metrics
from metricspark.operators import baselines, global_index, index, intermediate, search, updates, variants
from metricspark.plans import costmodel, measures, workloads
from metricspark.sources import tables

POINTS = {i: [float(x), float(y)] for i, (x, y) in workloads.LATTICE.items()}


@pytest.fixture(scope="module")
def pts(spark, sf):
    return tables.written(tables.load(spark, sf, "event_points"), "t")


@pytest.fixture(scope="module")
def asked(spark, sf):
    return tables.written(tables.frozen_queries(spark, sf, "event_points"), "t")


@pytest.fixture(scope="module")
def idx(pts):
    return index.build_index(pts, metrics.l2(), 2, n_p=30, n_w=4)


def pairs(df):
    return sorted((r.qid, r.oid, round(r.dist, 9)) for r in df.collect())


def ranks(df):
    return sorted((r.qid, r["rank"], r.oid, round(r.dist, 9)) for r in df.collect())


def test_thirteen_points_partition_as_printed():
    m = metrics.l2()
    tree = global_index.tree_from_levels([[POINTS[i] for i in (2, 3, 8)], [POINTS[i] for i in (4, 5, 7, 8, 10, 11)]], m)
    leaf, d = global_index._descend(m, tree, [POINTS[i] for i in range(1, 14)])
    groups = {}
    for i, n in zip(range(1, 14), leaf):
        groups.setdefault(tuple(tree.nodes[n].center), set()).add(i)
    by = {k: groups[tuple(POINTS[k])] for k in (4, 5, 7, 8, 10, 11)}
    assert by == {4: {1, 4, 12}, 7: {2, 7}, 11: {6, 11}, 5: {3, 5}, 8: {8, 13}, 10: {9, 10}}
    keys = {k: next(n.dist_to_parent for n in tree.nodes if n.level == 2 and n.center == POINTS[k]) for k in by}
    assert {k: round(v, 1) for k, v in keys.items()} == {4: 1.4, 7: 1.4, 11: 1.4, 5: 1.0, 8: 0.0, 10: 2.0}


def test_worked_examples(spark):
    rows = workloads.worked_examples(spark).collect()
    got = {}
    for r in rows:
        got.setdefault((r.objects, r.parameter), set()).add(int(r.value))
    assert got == {("strings", "range_1"): {1, 3}, ("strings", "knn_3"): {0, 1, 3}, ("points", "range_2sqrt2"): {8, 9, 10, 11, 13}, ("points", "knn_2"): {9, 13}}


def test_assignment_by_join_equals_the_broadcast_descent(spark, pts):
    m = metrics.l2()
    for fanout, height in ((8, 2), (4, 3)):
        tree = global_index.plan_tree([r.obj for r in pts.orderBy("oid").limit(40).collect()], fanout, m)
        assert tree.height == height
        rows = lambda df: {r.oid: (r.leaf, round(r.d_center, 12), [round(x, 12) for x in r.d_anc]) for r in df.collect()}
        assert rows(global_index.assign_by_join(pts, tree, m, 2)) == rows(global_index.assign(pts, tree, m))


def test_build_by_join_gives_the_same_index(pts, idx):
    other = index.build_index(pts, metrics.l2(), 2, n_p=30, n_w=4, broadcast_nodes=0)
    at = lambda i: {r.oid: (r.pid, r.lnode_id) for r in i.objects.select("oid", "pid", "lnode_id").collect()}
    assert at(other) == at(idx)


def test_every_level_is_nearest(idx):
    rows = global_index.verify_nearest(idx).collect()
    assert sorted(r.level for r in rows) == list(range(1, idx.height + 1)) and all(r.tested == idx.n and r.violated == 0 for r in rows)


def test_rerouted_objects_equal_a_new_descent(spark, pts):
    m = metrics.l2()
    tree = global_index.plan_tree([r.obj for r in pts.orderBy("oid").limit(20).collect()], 5, m)
    before = tables.written(global_index.assign(pts, tree, m), "t")
    fresh = {}
    for n, r in zip(tree.leaves()[::3], pts.orderBy(F.desc("oid")).limit(20).collect()):
        new = global_index.add_leaf(tree, n.node_id, r.obj, m)
        fresh.setdefault(n.parent_id, []).append(new)
    rows = lambda df: {r.oid: (r.leaf, round(r.d_center, 12), [round(x, 12) for x in r.d_anc]) for r in df.collect()}
    assert rows(global_index.reroute(before, tree, fresh, m)) == rows(global_index.assign(pts, tree, m))


def test_local_trees_have_levels_within_the_fanout(pts):
    i = index.build_index(pts, metrics.l2(), 2, n_p=4, n_w=2, fanout=5)
    assert i.local_height >= 3
    nodes = i.local_nodes
    tops = {r.pid: r["count"] for r in nodes.where("level = 1").groupBy("pid").count().collect()}
    assert max(tops.values()) <= 5 and len(tops) == i.placement.count()
    children = nodes.where("parent_id >= 0").groupBy("parent_id").count().agg(F.avg("count")).first()[0]
    assert children <= 7
    totals = nodes.groupBy("level").agg(F.sum("n_objects").alias("n"), F.max("is_leaf").alias("leaf")).where("not leaf").collect()
    assert all(r.n <= i.n for r in totals)
    assert nodes.where("is_leaf").agg(F.sum("n_objects")).first()[0] == i.n
    assert {r.rule: r.violated for r in global_index.verify(i).collect()} == dict.fromkeys(["has one partition", "within covering radius", "within local radius", "stored distance is right", "no object twice"], 0)


def test_fanout_and_tree_save_distances(pts, asked):
    calls = {}
    for fanout in (5, 400):
        i = index.build_index(pts, metrics.l2(), 2, n_p=4, n_w=2, fanout=fanout)
        calls[fanout] = measures.pruning(i, asked, 0.02).where("stage = 'objects'").first().survived
    assert calls[5] < calls[400]  # objects whose distance is computed


def test_knn_descends_the_tree_with_bounds(pts, asked):
    i = index.build_index(pts, metrics.l2(), 2, n_p=60, n_w=4, fanout=4)
    q = asked.withColumn("k", F.lit(3))
    reached = search.nearest_partitions(i, q)
    assert reached.count() < 0.5 * q.count() * i.placement.count()
    plan = reached._jdf.queryExecution().executedPlan().toString()
    assert plan.count("BroadcastNestedLoopJoin") == 1  # only the top level, of at most a fanout of nodes, meets all queries


def test_overflowing_partitions_split(pts, asked, monkeypatch):
    monkeypatch.setattr(updates, "OVERFLOW", 2)
    base = index.build_index(pts.where("oid % 10 = 1"), metrics.l2(), 2, n_p=10, n_w=3)
    crowd = pts.select((F.col("oid") + 100_000).alias("oid"), F.transform("obj", lambda x: F.lit(0.3) + x / 50).alias("obj"))
    grown = updates.insert(updates.insert(base, pts.where("oid % 10 <> 1")), crowd)
    assert grown.placement.count() > base.placement.count()
    assert grown.objects.count() == grown.n == 2 * pts.count() and grown.objects.select("oid").distinct().count() == grown.n
    cap = 2 * global_index.capacity(grown.n, 10)
    assert grown.placement.agg(F.max("n_objects")).first()[0] <= 2 * cap
    every = pts.select("oid", "obj").unionByName(crowd)
    assert pairs(search.range_query(grown, asked, 0.05)) == pairs(baselines.scan_range(every, metrics.l2(), asked, 0.05, 2))
    assert ranks(search.knn_query(grown, asked, 9)) == ranks(baselines.scan_knn(every, metrics.l2(), asked, 9, 2))
    assert {r.rule: r.violated for r in global_index.verify(grown).collect()} == dict.fromkeys(["has one partition", "within covering radius", "within local radius", "stored distance is right", "no object twice"], 0)


def test_many_queries_are_not_broadcast(pts, asked, monkeypatch):
    from metricspark.operators import sizes

    want = pairs(baselines.scan_range(pts, metrics.l2(), asked, 0.05, 2))
    monkeypatch.setattr(sizes.sized, "__defaults__", (2,))
    monkeypatch.setattr(search, "MOST_BYTES", 10)
    assert pairs(baselines.scan_range(pts, metrics.l2(), asked, 0.05, 2)) == want
    i = index.build_index(pts, metrics.l2(), 2, n_p=30, n_w=4)
    assert pairs(search.range_query(i, asked, 0.05)) == want


def test_boxes_of_the_layered_pivot_index_grow_with_the_objects(pts):
    n = lambda rows: baselines.layered_pivot_build(pts, metrics.l2(), dim=2, box_rows=rows).boxes.count()
    assert n(10) > n(200) > 1


def test_invariants(idx):
    assert {r.rule: r.violated for r in global_index.verify(idx).collect()} == dict.fromkeys(["has one partition", "within covering radius", "within local radius", "stored distance is right", "no object twice"], 0)


@pytest.mark.parametrize("options", [{}, {"placement": "random"}, {"placement": "homogeneous"}, {"local": "flat"}, {"local": "vantage"}, {"balance": "partitions"}])
def test_every_variant_equals_the_scan(pts, asked, options):
    i = index.build_index(pts, metrics.l2(), 2, n_p=25, n_w=3, **options)
    for r in (0.0, 0.05, 1.0, 50.0):
        assert pairs(search.range_query(i, asked, r)) == pairs(baselines.scan_range(pts, metrics.l2(), asked, r, 2))
    for k in (1, 8):
        assert ranks(search.knn_query(i, asked, k)) == ranks(baselines.scan_knn(pts, metrics.l2(), asked, k, 2))


def test_k_beyond_partition_and_beyond_all(spark):
    few = spark.createDataFrame([(i, [float(i % 4), 0.0]) for i in range(40)], "oid long, obj array<double>")
    q = few.where("oid < 3").select(F.col("oid").alias("qid"), F.col("obj").alias("q"))
    i = index.build_index(few, metrics.l2(), 2, n_p=8, n_w=2, fanout=3)
    for k in (1, 15, 100):
        assert ranks(search.knn_query(i, q, k)) == ranks(baselines.scan_knn(few, metrics.l2(), q, k, 2))


@pytest.mark.parametrize("rows", [[], [(1, [0.5, 0.5])], [(i, [1.0, 2.0]) for i in range(30)]])
def test_empty_single_and_identical(spark, rows):
    df = spark.createDataFrame(rows, "oid long, obj array<double>")
    q = spark.createDataFrame([(7, [1.0, 2.0])], "qid long, q array<double>")
    i = index.build_index(df, metrics.l2(), 2, n_p=4, n_w=2)
    assert i.n == len(rows)
    assert pairs(search.range_query(i, q, 0.0)) == pairs(baselines.scan_range(df, metrics.l2(), q, 0.0, 2))
    assert ranks(search.knn_query(i, q, 3)) == ranks(baselines.scan_knn(df, metrics.l2(), q, 3, 2))


def test_strings_with_empty_word(spark):
    df = spark.createDataFrame([(i, w) for i, w in enumerate(["", "a", "ab", "abc", "zzz", "", "bb", "aab"])], "oid long, obj string")
    q = df.where("oid in (0, 2)").select(F.col("oid").alias("qid"), F.col("obj").alias("q"))
    i = index.build_index(df, metrics.edit(), None, n_p=3, n_w=2, fanout=2)
    for r in (0, 1, 2, 30):
        assert pairs(search.range_query(i, q, r)) == pairs(baselines.scan_range(df, metrics.edit(), q, r))
    assert ranks(search.knn_query(i, q, 4)) == ranks(baselines.scan_knn(df, metrics.edit(), q, 4))


def test_count_exists_anti(idx, asked):
    n = {r.qid: r.n for r in search.range_count(idx, asked, 0.05).collect()}
    want = {}
    for q, *_ in pairs(search.range_query(idx, asked, 0.05)):
        want[q] = want.get(q, 0) + 1
    assert n == want
    some = {r.qid for r in search.range_exists(idx, asked, 0.01, True).collect()}
    none = {r.qid for r in search.range_anti(idx, asked, 0.01, True).collect()}
    assert not some & none and len(some | none) == asked.count()


def test_knn_is_the_range_of_the_kth_distance(idx, asked):
    assert ranks(search.knn_via_range(idx, asked, 6)) == ranks(search.knn_query(idx, asked, 6))


def test_bounds_are_sound(idx, asked):
    truth = {}
    for q, r, _, d in ranks(search.knn_query(idx, asked, 8)):
        truth[q] = max(truth.get(q, 0), d)
    for b in search.knn_bounds(idx, asked.withColumn("k", F.lit(8))).collect():
        assert b.d_k is None or b.d_k >= truth[b.qid] - 1e-9
        assert b.d_t is None or b.d_t >= truth[b.qid] - 1e-9


def test_validated_objects_are_answers(idx, asked):
    free = search.range_query(idx, asked, 1.0, with_dist=False)
    kinds = {r.decided_by for r in free.select("decided_by").distinct().collect()}
    assert "validated_cluster" in kinds and "validated_object" in kinds
    assert sorted((r.qid, r.oid) for r in free.collect()) == [x[:2] for x in pairs(search.range_query(idx, asked, 1.0))]


def test_pruning_saves_work(idx, asked):
    c = measures.stage_counts(idx, asked, 0.05).first()
    flat = measures.stage_counts(index.build_index(idx.objects.select("oid", "obj"), metrics.l2(), 2, n_p=30, local="flat"), asked, 0.05).first()
    assert c.verified <= flat.verified <= c.objects * c.n_queries and c.verified < c.objects * c.n_queries / 4
    work = measures.workload(idx, asked, 0.05)
    assert work.count() == idx.n_w and sum(r.answers for r in work.collect()) == len(pairs(search.range_query(idx, asked, 0.05)))
    rows = {r.stage: r for r in measures.pruning(idx, asked, 0.05).collect()}
    assert rows["partitions"].filtered + rows["partitions"].validated + rows["partitions"].survived == rows["partitions"].distance_calls


def test_packing_keeps_order_and_balance(spark):
    parts = spark.createDataFrame([(i, float((i * 7) % 11), 10 + i % 3) for i in range(23)], "pid long, dist_to_parent double, n_objects long")
    for balance in ("partitions", "objects"):
        rows = intermediate.deal(intermediate.pack(parts, 4, balance), 3).orderBy("dist_to_parent", "pid").collect()
        buckets = [r.bucket for r in rows]
        assert buckets == sorted(buckets) and max(buckets) == 5
        assert all(r.slot == r.bucket % 3 for r in rows)
        sizes = [buckets.count(b) for b in set(buckets)]
        if balance == "partitions":
            assert max(sizes) - min(sizes) <= 1


def test_ordered_index():
    rng = np.random.default_rng(4)
    entries = [(float(rng.integers(0, 20)), i) for i in range(200)]
    t = intermediate.OrderedLeafIndex(entries[:150], 8)
    for key, pid in entries[150:]:
        t.insert(key, pid)
    for _, pid in entries[:40]:
        t.remove(pid)
    left = sorted(entries[40:])
    assert t.entries() == left and all(len(x) <= 8 for x in t.leaves)
    assert sorted(t.range(3.0, 9.0)) == sorted(p for k, p in left if 3 <= k <= 9)
    assert all(t.lookup(p) == t.lookup_linear(p) for _, p in left) and t.lookup(0) is None


def test_updates_equal_a_rebuild(pts, asked):
    base = index.build_index(pts.where("oid % 5 <> 1"), metrics.l2(), 2, n_p=20)
    grown = updates.insert(base, pts.where("oid % 5 = 1"))
    cut = updates.delete(grown, pts.where("oid % 4 = 2").select("oid"))
    left = pts.where("oid % 4 <> 2")
    for i in (cut, updates.compact(cut)):
        assert pairs(search.range_query(i, asked, 0.1)) == pairs(baselines.scan_range(left, metrics.l2(), asked, 0.1, 2))
        assert ranks(search.knn_query(i, asked, 9)) == ranks(baselines.scan_knn(left, metrics.l2(), asked, 9, 2))


def test_same_index_whatever_the_layout(pts, idx):
    other = index.build_index(pts.repartition(7), metrics.l2(), 2, n_p=30, n_w=4)
    at = lambda i: {r.oid: (r.pid, r.slot, r.lnode_id) for r in i.objects.select("oid", "pid", "slot", "lnode_id").collect()}
    assert at(other) == at(idx)


def test_reopened_index_answers_alike(spark, idx, asked):
    assert pairs(search.range_query(index.open_index(spark, idx.path), asked, 0.05)) == pairs(search.range_query(idx, asked, 0.05))


def test_baselines_equal_the_scan(pts, asked):
    m = metrics.l2()
    want, best = pairs(baselines.scan_range(pts, m, asked, 0.1, 2)), ranks(baselines.scan_knn(pts, m, asked, 5, 2))
    pk, lp = baselines.pivot_key_build(pts, m, 12, dim=2), baselines.layered_pivot_build(pts, m, dim=2)
    assert pairs(baselines.pivot_key_range(pk, asked, 0.1)) == want and ranks(baselines.pivot_key_knn(pk, asked, 5)) == best
    assert pairs(baselines.layered_pivot_range(lp, asked, 0.1)) == want and ranks(baselines.layered_pivot_knn(lp, asked, 5)) == best
    assert pairs(baselines.single_mtree(pts, m, asked, r=0.1)) == want and ranks(baselines.single_mtree(pts, m, asked, k=5)) == best
    assert pairs(baselines.grid_range(pts, asked, 0.1)) == want


def test_single_tree_takes_any_number_of_queries(pts, asked, monkeypatch):
    monkeypatch.setattr(baselines, "MOST_ROWS", 3)  # the bound of methods that hand the queries to every task
    monkeypatch.setattr(baselines, "MOST_PAIRS", 50)
    monkeypatch.setattr(baselines, "LEAF_OBJECTS", 5)
    m, copies = metrics.l2(), pts.unionByName(pts.select((F.col("oid") + 1_000_000).alias("oid"), "obj"))
    assert ranks(baselines.single_mtree(copies, m, asked, k=3)) == ranks(baselines.scan_knn(copies, m, asked, 3, 2))
    assert pairs(baselines.single_mtree(copies, m, asked, r=0.05)) == pairs(baselines.scan_range(copies, m, asked, 0.05, 2))


def test_single_tree_of_words(spark):
    words = spark.createDataFrame([(i, w) for i, w in enumerate("ring rings king kin bolt bolts ring cold".split())] + [(9, None)], "oid long, obj string")
    q, m = words.where("oid < 5").selectExpr("oid as qid", "obj as q"), metrics.edit()
    some = words.where("obj is not null")
    assert ranks(baselines.single_mtree(words, m, q, k=3, n_p=3, fanout=2)) == ranks(baselines.scan_knn(some, m, q, 3))


def test_knn_meets_few_copies_of_a_string(spark):
    names = [(i, ["red ring", "red bolt", "old plate", "hot gear"][i % 4]) for i in range(400)] + [(1000, "cold gears"), (1001, "ring")]
    words, m = spark.createDataFrame(names, "oid long, obj string"), metrics.edit()
    q = words.where("oid % 50 = 0 or oid > 999").selectExpr("oid as qid", "obj as q").unionByName(spark.createDataFrame([(-1, None)], "qid long, q string"))
    for local in ("tree", "vantage"):
        i = index.build_index(words, m, n_p=4, n_w=2, local=local)
        assert ranks(search.knn_query(i, q, 5)) == ranks(baselines.scan_knn(words, m, q.where("q is not null"), 5))
        few = search._without_copies(i, 5).objects
        assert few.where("obj = 'red ring' and rank_v < 0").count() <= 5 if local == "tree" else few.count() < 60
        asked = q.selectExpr("qid", "q", "case when qid % 100 = 0 then 2 else 3 end as k")
        got = search.knn_query(i, asked).groupBy("qid").count().join(asked, "qid").where("count <> k")
        assert got.count() == 0


def test_knn_of_vectors_that_nothing_prunes(spark, sf, monkeypatch):
    monkeypatch.setattr(search, "PRODUCT_ROWS", 150)
    monkeypatch.setattr(search, "PRODUCT_QUERIES", 40)
    objs = tables.load(spark, sf, "embed_l2").where("oid < 300")
    objs = tables.written(objs.unionByName(objs.where("oid < 9").select((F.col("oid") + 1000).alias("oid"), "obj")).unionByName(objs.where("oid = 7").crossJoin(spark.range(2000, 2050)).selectExpr("id as oid", "obj")), "t")
    m, i = metrics.l2(), index.build_index(objs, metrics.l2(), 64, n_p=10, n_w=2)
    q = objs.where("oid < 60 or oid > 2040").selectExpr("oid as qid", "obj as q")
    assert search.nothing_prunes(i, q.withColumn("k", F.lit(3)))
    assert ranks(search.knn_query(i, q, 3)) == ranks(baselines.scan_knn(objs, m, q, 3, 64))
    assert "reached" not in search.knn_query(i, q, 3)._jdf.queryExecution().toString()  # no row a query and partition
    few = ranks(search.knn_query(i, q.selectExpr("qid", "q", "case when qid % 2 = 0 then 1 else 400 end as k")))
    full = ranks(baselines.scan_knn(objs, m, q, 400, 64))
    assert few == [r for r in full if r[0] % 2 or r[1] == 1]


def test_graph_baseline_is_near_and_has_no_range(pts, asked):
    m = metrics.l2()
    got = measures.recall(baselines.graph_ann_knn(pts, m, asked, 5), baselines.scan_knn(pts, m, asked, 5, 2)).first().recall
    assert got >= 0.9
    with pytest.raises(baselines.NotSupported):
        baselines.graph_ann_range(pts)


def test_placements_keep_all_objects(idx):
    o = idx.objects.drop("slot")
    for df in (variants.cluster_id_round_robin(o, 4), variants.heterogeneous_placement(o, 4)):
        n = [r.n for r in df.groupBy("slot").agg(F.count("*").alias("n")).collect()]
        assert sum(n) == idx.n and max(n) < 2 * min(n)
    assert variants.replicated_placement(idx.placement, 4, 2).count() == 2 * idx.placement.count()


def test_plans(idx, asked):
    plan = search.range_query(idx, asked, 0.05)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BatchEvalPython" not in plan and "MapInArrow" not in plan
    build = idx.objects.sparkSession.read.parquet(f"{idx.path}/objects").where("slot = 2")._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [isnotnull(slot" in build


def test_cost_model():
    s = costmodel.Setting(1e7, 10, 20, 1, 0.01)
    n_p, why = costmodel.solve_n_p(s)
    assert why == "ok" and 150 < n_p < 190
    around = [costmodel.total_cost(s, n_p * f) for f in (0.8, 1, 1.25)]
    assert around[1] == min(around)
    eps = 1e-3
    slope = (costmodel.total_cost(s, 300 + eps) - costmodel.total_cost(s, 300 - eps)) / (2 * eps)
    left, right = costmodel.optimality(s, 300)
    assert (slope > 0) == (left > right)
    assert costmodel.solve_n_p(costmodel.Setting(1e7, 10, 20, 1, 0.5)) == (None, "no_root")
    assert costmodel.solve_n_p(costmodel.Setting(1e7, 10, 20, 1, -3.0)) == (None, "lambda_out_of_range")
    assert costmodel.survival(1.0, 2.0, 2) == 0.25 and costmodel.space(100, 10, 5)["worker"] == 20


def test_homogeneous_placement_is_less_even_on_a_hot_spot(pts):
    near = baselines.scan_knn(pts, metrics.l2(), pts.orderBy("oid").limit(1).select(F.col("oid").alias("qid"), F.col("obj").alias("q")), 60, 2)
    q = pts.join(near.select(F.col("oid").alias("n_")), F.col("oid") == F.col("n_")).select(F.col("oid").alias("qid"), F.col("obj").alias("q"))
    total = {"packed": 0.0, "homogeneous": 0.0}
    for seed in (1, 2, 3):
        for placement in total:
            i = index.build_index(pts, metrics.l2(), 2, n_p=60, n_w=5, seed=seed, placement=placement)
            total[placement] += measures.load_deviation(measures.workload(i, q, 0.05), "verified").first().variation
    assert total["packed"] < total["homogeneous"]


def test_pivot_knn_of_an_outlier(spark):
    rng = np.random.default_rng(8)
    rows = [(i, [float(x), float(y)]) for i, (x, y) in enumerate(rng.random((400, 2)))] + [(400, [1000.0, 1000.0])]
    objs, m = tables.written(spark.createDataFrame(rows, "oid long, obj array<double>"), "t"), metrics.l2()
    q = objs.where("oid in (0, 400)").select(F.col("oid").alias("qid"), F.col("obj").alias("q"))
    best = ranks(baselines.scan_knn(objs, m, q, 5, 2))
    assert len(best) == 10
    assert ranks(baselines.pivot_key_knn(baselines.pivot_key_build(objs, m, 8, dim=2), q, 5)) == best
    assert ranks(baselines.layered_pivot_knn(baselines.layered_pivot_build(objs, m, dim=2), q, 5)) == best


def test_knn_passes_on_no_more_than_k_a_tree(spark):
    """Copies of points: before ranking, each local tree gives a query its k nearest, the smallest oids of equal ones, and no pair is sorted or kept."""
    rng = np.random.default_rng(8)
    pts = rng.random((100, 2)).round(2).tolist()
    df = spark.createDataFrame([(i, pts[i % 100]) for i in range(3000)], "oid long, obj array<double>")
    q = df.where("oid % 50 = 0").select(F.col("oid").alias("qid"), F.col("obj").alias("q"))
    for local in ("tree", "flat", "vantage"):
        i = index.build_index(df, metrics.l2(), 2, n_p=8, n_w=2, local=local)
        asked_ = q.withColumn("k", F.lit(5))
        most = search.knn_by_partition(i, asked_).groupBy("qid").count().agg(F.max("count").alias("m")).first().m
        assert most <= 5 * len(i.tree.leaves())
        assert ranks(search.knn_query(i, q, 5)) == ranks(baselines.scan_knn(df, metrics.l2(), q, 5, 2))


def test_blocks_pass_on_k_rows_a_query(spark):
    """The exhaustive searches send k rows a query and block to the ranking, in the metric's order."""
    df = spark.createDataFrame([(i, [float(i % 7), float(i % 5)]) for i in range(400)], "oid long, obj array<double>")
    q = df.where("oid % 50 = 0").select(F.col("oid").alias("qid"), F.col("obj").alias("q"))
    got = search.nearest_by_block(df, metrics.l2(), q, 3, 4, F.pmod("oid", F.lit(4)), 2)
    assert got.groupBy("qid").count().agg(F.max("count").alias("m")).first().m <= 7 * 5 * 3
    assert ranks(search.rank_answers(got)) == ranks(baselines.scan_knn(df, metrics.l2(), q, 3, 2))


def test_knn_goes_by_the_vantage_distances(spark, pts, asked):
    """The stored distances to the vantage objects decide which objects are measured, and an index without some of them stays exact."""
    m = metrics.l2()
    i = index.build_index(pts, m, 2, n_p=6, n_w=2, local="vantage")
    best = ranks(baselines.scan_knn(pts, m, asked, 4, 2))
    assert ranks(search.knn_query(i, asked, 4)) == best
    moved = i.with_objects(i.objects.withColumn("dv", F.transform("dv", lambda x: x + 1000)))
    assert search.knn_query(moved, asked, 4).count() == 0
    unstored = i.with_objects(i.objects.withColumn("dv", F.when(F.col("oid") % 3 == 0, F.array().cast("array<double>")).otherwise(F.col("dv"))))
    assert ranks(search.knn_query(unstored, asked, 4)) == best
    kept = i.with_objects(i.objects.where("rank_v <> 0"))
    left = pts.join(kept.objects.select(F.col("oid").alias("k_")), F.col("oid") == F.col("k_"), "left_semi")
    assert left.count() < pts.count() and ranks(search.knn_query(kept, asked, 4)) == ranks(baselines.scan_knn(left, m, asked, 4, 2))


def test_vantage_cells_leave_few_objects_to_measure(spark):
    import pyarrow as pa

    rng, m, measured = np.random.default_rng(3), metrics.l2(), []
    x = rng.random((4000, 2))
    far = np.stack([m.kernel(x, x[i]) for i in range(3)], axis=1)
    cell = np.argsort(np.argsort(far[:, 0])) // 80
    rows = pa.table({"lnode_id": [0] * 4000, "oid": range(4000), "obj": x.tolist(), "d_leaf": far[:, 0], "level": pa.array([None] * 4000, pa.int32()), "dv": far.tolist(), "rank_v": list(range(3)) + [-1] * 3997, "cell": cell})
    q = pa.table({"qid": [1, 2], "q": [[0.3, 0.4], [0.9, 0.9]], "k": [5, 5], "r": [0.05, np.inf]})
    counting = metrics.register("counted_l2", m.column, lambda many, one: (measured.append(len(many)), m.kernel(many, one))[1])
    got = search._near_rows(counting, 2)(rows, q).to_pylist()
    for qid, one in ((1, [0.3, 0.4]), (2, [0.9, 0.9])):
        d = m.kernel(x, np.array(one))
        assert [r["oid"] for r in got if r["qid"] == qid] == np.argsort(d)[:5].tolist()
    assert max(measured[:2]) < 400  # its three vantage objects and what they leave of 4000


def test_extremes_by_block_equal_all_pairs(spark, monkeypatch):
    """Far and near runs are left out, and the rest equals all pairs, with copies, one far point, and values that are no numbers."""
    from metricspark.operators import blocks

    rng = np.random.default_rng(5)
    x = np.vstack([rng.random((6000, 2)), np.repeat([[0.5, 0.5]], 200, axis=0), [[1e6, -3.0]]])
    measured = []
    for m in (metrics.l1(), metrics.l2(), metrics.lp(3), metrics.lp(1.5), metrics.linf()):
        q, (sums, root) = x[::2], m.crossed
        counting = replace(m, crossed=(lambda a, b: (measured.append(len(a) * len(b)), sums(a, b))[1], root))
        measured.clear()
        least, most = blocks.extremes(counting, x, q)
        d = np.stack([m.kernel(x, o) for o in q], axis=1)
        assert np.allclose(least, d.min(axis=1), rtol=1e-12, atol=1e-15) and np.allclose(most, d.max(axis=1), rtol=1e-12)
        assert sum(measured) < d.size / 2
    odd = np.vstack([x[:100], [[np.nan, 1.0], [np.inf, 1.0]]])
    with np.errstate(invalid="ignore"):
        least, most = blocks.extremes(metrics.l2(), odd, odd[:50])
        assert np.isnan(least[100]) and np.isnan(most[100]) and least[101] == most[101] == np.inf and not least[:50].any()
        assert np.isnan(blocks.extremes(metrics.l2(), odd, odd)[1]).all() and not blocks.extremes(metrics.l2(), odd, odd)[0][:100].any()
    monkeypatch.setattr(search, "EXTREME_ROWS", 90)
    df = spark.createDataFrame([(i % 300, p) for i, p in enumerate(x[:320].tolist())], "oid long, obj array<double>")
    q = df.where("oid % 2 = 0").selectExpr("oid as qid", "obj as q")
    got = {r.oid: (r.nearest, r.farthest) for r in search.extremes_by_block(df, metrics.lp(3), q).collect()}
    pairs_ = df.crossJoin(q).groupBy("oid").agg(F.min(metrics.lp(3).column(F.col("q"), F.col("obj"), 2)), F.max(metrics.lp(3).column(F.col("q"), F.col("obj"), 2))).collect()
    assert len(got) == 300 and all(np.allclose(got[r[0]], r[1:], rtol=1e-12, atol=1e-15) for r in pairs_)


def test_nearest_of_a_block_equals_all_pairs():
    """The k nearest of a block with copies and ties, for more than it holds as well, by a small part of the pairs."""
    from metricspark.operators import blocks

    rng, measured = np.random.default_rng(6), []
    x = np.vstack([rng.random((4000, 2)), rng.random((400, 2)).round(1), np.repeat([[0.5, 0.5]], 300, axis=0), [[1e6, -3.0]]])
    oid, asked_ = rng.permutation(len(x)), np.vstack([x[::4], [[7.0, 7.0]]])
    for m in (metrics.l1(), metrics.l2(), metrics.lp(3), metrics.linf()):
        sums, root = m.crossed
        counting = replace(m, crossed=(lambda a, b: (measured.append(len(a) * len(b)), sums(a, b))[1], root))
        for k in (1, 5, 100, 10_000):
            measured.clear()
            q = asked_ if k < 1000 else asked_[-40:]
            of, who, d = blocks.nearest_of_block(counting, x, oid, q, k)
            for i in range(0, len(q), 9):
                far = m.kernel(x, q[i]).round(9)
                mine = np.flatnonzero(of == i)
                order = mine[np.lexsort((who[mine], d[mine].round(9)))][:k]
                assert who[order].tolist() == oid[np.lexsort((oid, far))][:k].tolist()
            assert k > 5 or sum(measured) < len(x) * len(q) / 2
