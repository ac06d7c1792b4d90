"""SQL surface: distance functions, and table functions that give the candidate partitions of a query."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..operators.index import MetricIndex

# Distances as SQL functions: no Python at run time.
FUNCTIONS = {
    "l1_distance": ("a array<double>, b array<double>", "double", "aggregate(zip_with(a, b, (x, y) -> abs(x - y)), 0.0D, (s, x) -> s + x)"),
    "l2_distance": ("a array<double>, b array<double>", "double", "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0.0D, (s, x) -> s + x))"),
    "linf_distance": ("a array<double>, b array<double>", "double", "array_max(zip_with(a, b, (x, y) -> abs(x - y)))"),
    "edit_distance": ("a string, b string", "int", "levenshtein(a, b)"),
}


def register_functions(spark: SparkSession) -> None:
    for name, (args, kind, body) in FUNCTIONS.items():
        spark.sql(f"create or replace temporary function {name}({args}) returns {kind} return {body}")


def register_index(spark: SparkSession, idx: MetricIndex, name: str) -> None:
    """Views `{name}_objects` and `{name}_placement`, and table functions `{name}_range(q, r)` and `{name}_knn(q, k)`.

    The table functions walk the tree (about N_p nodes, shipped once) and give (pid, bound) only: a function on an
    executor must not start jobs, so objects are joined outside on pid and verified there.
    """
    tree, metric = idx.tree, idx.metric
    loose = lambda r: r if metric.integer_valued else r * (1 + 1e-9) + 1e-12

    def far(q, ids):
        """(node, distance) of some nodes, in one call of the kernel."""
        import numpy as np

        nodes = [tree.nodes[i] for i in ids if tree.nodes[i].n_objects]
        if not nodes:
            return []
        q = q if isinstance(q, str) else np.asarray(q, float)
        return list(zip(nodes, metric.kernel(metric.batch([n.center for n in nodes]), q).tolist()))

    class Range:
        def eval(self, q, r):
            front = far(q, tree.top())
            while front:
                kept = [(n, d) for n, d in front if d <= loose(r) + n.radius]
                for n, _ in kept:
                    if n.pid >= 0:
                        yield n.pid, float(r)
                # children that the distance between centres excludes need no distance of their own
                front = far(q, [c for n, d in kept for c in n.children if abs(tree.nodes[c].dist_to_parent - d) <= loose(r) + tree.nodes[c].radius])

    class Knn:
        def eval(self, q, k):
            front, bound, found = far(q, tree.top()), float("inf"), []
            while front:
                held = 0
                for n, d in sorted(front, key=lambda x: x[1] + x[0].radius):
                    held += n.n_objects
                    if held >= k:
                        bound = min(bound, d + n.radius)
                        break
                kept = [(n, d) for n, d in front if d - n.radius <= loose(bound)]
                found += [(n, d) for n, d in kept if n.pid >= 0]
                front = far(q, [c for n, d in kept for c in n.children if abs(tree.nodes[c].dist_to_parent - d) <= loose(bound) + tree.nodes[c].radius])
            for n, d in found:
                if d - n.radius <= loose(bound):
                    yield n.pid, bound

    spark.udtf.register(f"{name}_range", F.udtf(Range, returnType="pid bigint, bound double"))
    spark.udtf.register(f"{name}_knn", F.udtf(Knn, returnType="pid bigint, bound double"))
    idx.objects.createOrReplaceTempView(f"{name}_objects")
    idx.placement.createOrReplaceTempView(f"{name}_placement")


def covering_radius(objects: DataFrame) -> DataFrame:
    """[pid, radius] by the built-in maximum."""
    return objects.groupBy("pid").agg(F.max("d_center").alias("radius"))


def medoids(objects: DataFrame, metric, groups: str = "lnode_id") -> DataFrame:
    """[group, oid]: the member with the least sum of distances in each local cluster (clusters are small)."""
    import numpy as np
    import pandas as pd

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        objs = [o if isinstance(o, str) else list(o) for o in pdf["obj"]]
        batch = metric.batch(objs)
        sums = np.array([metric.kernel(batch, o if isinstance(o, str) else np.asarray(o, float)).sum() for o in objs])
        best = min(range(len(objs)), key=lambda i: (round(sums[i], 9), pdf["oid"].iloc[i]))
        return pd.DataFrame({"group": [key[0]], "oid": [int(pdf["oid"].iloc[best])]})

    return objects.select(F.col(groups).cast("long").alias("g_"), "oid", "obj").groupBy("g_").applyInPandas(run, "group long, oid long")


def distance_udf(metric, one):
    """A vectorised function: distances of a column's objects to `one`, a batch at a time in NumPy."""
    import numpy as np
    import pandas as pd

    q = one if isinstance(one, str) else np.asarray(one, float)

    def distance(objs):
        return pd.Series(metric.kernel(metric.batch([o if isinstance(o, str) else list(o) for o in objs]), q) if len(objs) else [], dtype=float)

    distance.__annotations__ = {"objs": pd.Series, "return": pd.Series}  # the kind of function is read off these
    return F.pandas_udf(distance, "double")


def distance_histogram(objects: DataFrame, metric, n: int = 200, steps: int = 20, dim: int | None = None) -> DataFrame:
    """[share, distance]: quantiles of sampled distances from a mergeable sketch."""
    from ..operators.sampling import pair_distances

    shares = [k / steps for k in range(steps + 1)]
    sketch = pair_distances(objects, metric, n, 11, dim).agg(F.kll_sketch_agg_double("d").alias("s"))
    return sketch.select(F.explode(F.array(*[F.struct(F.lit(x).alias("share"), F.kll_sketch_get_quantile_double("s", F.lit(x)).alias("distance")) for x in shares])).alias("q")).select("q.*")


def top_k_aggregate(objects: DataFrame, metric, queries: DataFrame, k: int, dim: int | None = None, lanes: int = 64) -> DataFrame:
    """[qid, rank, oid, dist]: per query and lane the k best, then the k best of the lanes; each state is bounded by k rows."""
    from ..operators.search import BLOCK, nearest_by_block, rank_answers
    from ..operators.sizes import sized

    if metric.kind == "vector":
        lanes = max(lanes, -(-objects.count() // BLOCK))
        return rank_answers(nearest_by_block(objects, metric, queries, k, lanes, F.pmod(F.xxhash64("oid"), F.lit(lanes)), dim))
    near = objects.select("oid", "obj").crossJoin(sized(queries.select("qid", "q")))
    near = near.select("qid", "oid", metric.column(F.col("q"), F.col("obj"), dim).alias("dist"), F.pmod("oid", F.lit(lanes)).alias("lane"))
    first = Window.partitionBy("qid", "lane").orderBy(F.round("dist", 9), "oid")
    return rank_answers(near.withColumn("r_", F.row_number().over(first)).where(F.col("r_") <= k).withColumn("k", F.lit(k)))
