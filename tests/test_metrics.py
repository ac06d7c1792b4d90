import numpy as np
from pyspark.sql import functions as F

from metricspark.functions import metrics
from metricspark.operators.sampling import distance_stats, hash_sample, radius_for
from metricspark.sources import tables


def slow_edit(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def test_worked_strings(spark):
    want = {"00100": 2, "10111": 1, "01001": 3, "0110": 1}
    m = metrics.edit()
    assert dict(zip(want, m.kernel(m.batch(list(want)), "10110"))) == want
    df = spark.createDataFrame([(w,) for w in want], "w string")
    assert {r.w: r.d for r in df.select("w", m.column(F.col("w"), F.lit("10110"), None).alias("d")).collect()} == want


def test_edit_kernel_against_recurrence():
    rng = np.random.default_rng(3)
    words = ["".join(rng.choice(list("abcé"), rng.integers(0, 9))) for _ in range(60)]
    m = metrics.edit()
    for q in words[:12]:
        assert m.kernel(m.batch(words), q).tolist() == [slow_edit(w, q) for w in words]


def test_vector_kernels_equal_columns(spark):
    rng = np.random.default_rng(1)
    for dim in (1, 2, 5, 40):
        x, q = rng.normal(size=(20, dim)), rng.normal(size=dim)
        df = spark.createDataFrame([(v.tolist(), q.tolist()) for v in x], "a array<double>, b array<double>")
        for m in (metrics.l1(), metrics.l2(), metrics.linf(), metrics.lp(3)):
            got = [r.d for r in df.select(m.column(F.col("a"), F.col("b"), dim).alias("d")).collect()]
            assert np.allclose(sorted(got), sorted(m.kernel(x, q)))


def test_axioms_hold_and_a_false_metric_is_caught(spark, sf):
    pts = tables.load(spark, sf, "event_points")
    assert {r.violated for r in metrics.check_axioms(pts, metrics.l2(), 15, dim=2).collect()} == {0}
    squared = metrics.register("squared", lambda a, b: (a[0] - b[0]) ** 2 + (a[1] - b[1]) ** 2, lambda x, o: ((x - o) ** 2).sum(axis=1))
    bad = {r.axiom: r.violated for r in metrics.check_axioms(pts, squared, 15, dim=2).collect()}
    assert bad["triangle"] > 0 and bad["symmetry"] == 0


def test_samples_do_not_depend_on_layout(spark, sf):
    pts = tables.load(spark, sf, "event_points")
    a = [r.oid for r in hash_sample(pts, 20, 5).collect()]
    assert a == [r.oid for r in hash_sample(pts.repartition(7), 20, 5).collect()]


def test_statistics_and_radius(spark, sf):
    pts = tables.load(spark, sf, "event_points")
    s = distance_stats(pts, metrics.l2(), 100, dim=2).first()
    assert 0 < s.mean < s.max and s.variance > 0
    small, large = (radius_for(pts, metrics.l2(), p, dim=2) for p in (0.8, 3.2))
    assert 0 < small < large
    assert radius_for(pts, metrics.l2(), 10, mode="max_share", dim=2) > 0


def test_bad_objects_are_counted_and_left_out(spark):
    df = spark.createDataFrame([(1, [0.0, 1.0]), (2, None), (3, [float("nan"), 1.0]), (4, [1.0]), (5, [None, 1.0])], "oid long, obj array<double>")
    assert {r.reason: r.n for r in tables.rejected(df, metrics.l2(), 2).collect()} == {"null": 1, "not finite": 2, "wrong length": 1}
    assert [r.oid for r in tables.accepted(df, metrics.l2(), 2).collect()] == [1]


def test_rows_add_in_the_order_of_components():
    """As SQL does, so that a pair at the radius falls on the same side."""
    rng = np.random.default_rng(5)
    x, y = rng.random((300, 26)), rng.random((300, 26))
    for m, each, last in ((metrics.l1(), abs, float), (metrics.l2(), lambda d: d * d, np.sqrt)):
        want = []
        for a, b in zip(x, y):
            total = 0.0
            for p, q in zip(a, b):
                total += each(p - q)
            want.append(last(total))
        assert m.rows(x, y).tolist() == want


def test_edit_extremes_equal_single_distances(spark, monkeypatch):
    from metricspark.operators import search

    rng = np.random.default_rng(5)
    words = ["".join(rng.choice(list("abé\U0001f600"), rng.integers(0, 12))) for _ in range(60)] + ["http://a.example/" + str(i) * 3 for i in range(40)]
    words += ["ab" * n for n in (31, 32, 33, 40, 200)] + ["a" * 64, "b" * 65, "a" * 300 + "x", "a" * 300 + "y", words[0]]
    objs = spark.createDataFrame(list(enumerate(words)), "oid long, obj string")
    asked = objs.where("oid % 3 = 0 or length(obj) > 60").selectExpr("oid as qid", "obj as q")
    d = F.levenshtein("obj", "q").cast("double")
    want = {tuple(r) for r in objs.crossJoin(asked).groupBy("oid").agg(F.min(d), F.max(d)).collect()}
    monkeypatch.setattr(search, "EDIT_TEXTS", 40)
    monkeypatch.setattr(search, "EDIT_QUERIES", 30)
    monkeypatch.setattr(metrics, "LANES", 16)
    assert {tuple(r) for r in search.edit_extremes_by_block(objs, asked).collect()} == want
    assert search.edit_extremes_by_block(objs, asked.limit(0)).count() == 0
