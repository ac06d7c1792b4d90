"""Each corpus operator against a brute-force version, with nulls, empty and long texts, ties, repeats, empty tables and clashing columns."""
import hashlib
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from metricspark.llm import components, decontaminate, language_id, mixing, pii, quality, queries, secrets, simhash, token_files, topk, toxicity
from metricspark.llm.common import labelled_documents, lean, table


def docs_of(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string")


ODD = [(1, None), (2, ""), (3, "  \n\t "), (4, "word " * 60_000), (5, "same text here"), (5, "same text here"), (None, "no id at all"), (6, "é中 😀 x"), (7, "same text here")]


@pytest.fixture(scope="module")
def docs(spark, sf):
    return table(spark, sf, "documents")


@pytest.fixture(scope="module")
def local(docs):
    return {r.doc_id: r for r in docs.collect()}


# 1


def brute_top(vectors, queries_, k):
    ok = {}
    for i, v in vectors:
        if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v):
            ok.setdefault(i, []).append([int(np.floor(256 * float(x))) for x in v])
    out = []
    for q in sorted(set(queries_) & set(ok)):
        best = {}
        for i, vs in ok.items():
            for v in vs if i != q else ():
                s = sum(a * b for a, b in zip(ok[q][0], v))
                best[i] = max(best.get(i, s), s)
        out += [(q, n + 1, i, s) for n, (s, i) in enumerate(sorted((-s, i) for i, s in best.items())[:k])]
    return sorted((q, n, i, -s) for q, n, i, s in out)


def test_topk_against_brute_force(spark):
    rng = np.random.default_rng(5)
    rows = [(int(i), [float(x) for x in rng.normal(size=12)]) for i in range(300)]
    rows += [(300, None), (301, [1.0, None]), (302, [float("nan")] * 12), (None, [1.0] * 12), (350, [3.0]), (351, rows[0][1]), (352, rows[0][1]), (7, rows[9][1]), (400, [])]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("score", F.lit("clash"))
    got = sorted(tuple(r) for r in topk.top_k(v, v.where("vec_id % 50 = 0")).collect())
    assert got == brute_top(rows, [i for i, _ in rows if i is not None and i % 50 == 0], 5)
    assert topk.top_k(v.limit(0), v.limit(0)).count() == 0


def test_topk_few_candidates_and_large_values(spark):
    v = spark.createDataFrame([(0, [1e5, -2e5]), (1, [1e5, 3e5]), (2, [-1e5, 1.0])], "vec_id long, embedding array<double>")
    got = sorted(tuple(r) for r in topk.top_k(v, v.where("vec_id = 0")).collect())
    assert got == brute_top([(r.vec_id, r.embedding) for r in v.collect()], [0], 5)


# 2, 3


def test_toxicity_learns_and_locates(spark):
    rng = np.random.default_rng(2)
    calm = ["the", "house", "river", "stone", "walks", "green", "tree", "song"]
    rows = []
    for i in range(600):
        body = [" ".join(rng.choice(calm, 6)) for _ in range(int(rng.integers(2, 9)))]
        bad = int(i % 3 == 0)
        if bad:
            k = int(rng.integers(0, len(body)))
            body[k] = body[k] + " " + rng.choice(["vileword", "vileness"])
        rows.append((". ".join(body) + ".", bad))
    model = toxicity.fit_texts(rows[:400])
    got = [model.document(t) for t, _ in rows[400:]]
    assert np.mean([(p >= 0.5) == y for (p, *_), (_, y) in zip(got, rows[400:])]) > 0.95
    for (p, n, a, b), (t, y) in zip(got, rows[400:]):
        if y and p >= 0.5:
            assert n >= 1 and "vile" in t[a:b]
    assert model.document("") == (0.0, 0, -1, -1)
    kept = toxicity.drop_toxic(docs_of(spark, [(1, rows[0][0]), (2, rows[1][0]), (3, None)]).withColumn("score", F.lit(1)), model)
    assert sorted(r.doc_id for r in kept.collect()) == [2, 3] and kept.columns == ["doc_id", "text", "score"]


def test_toxicity_without_both_classes():
    assert toxicity.fit_texts([]).document("any text")[0] < 0.05
    assert toxicity.fit_texts([("a b", 0)]).weights == {}


def test_toxicity_of_a_table_equals_that_of_texts(spark):
    rng = np.random.default_rng(4)
    calm = [f"{a}{b}" for a in ("hou", "riv", "sto", "gre") for b in ("se", "er", "ne", "en", "ly")]
    rows = []
    for i in range(300):
        body = [" ".join(rng.choice(calm, 5)) for _ in range(int(rng.integers(1, 6)))]
        if i % 4 == 0:
            body[0] += " vile" + rng.choice(calm)
        rows.append((i, ". ".join(body), int(i % 4 == 0)))
    d = spark.createDataFrame(rows, "doc_id long, text string, y int")
    a, b = toxicity.fit_toxicity(d, rounds=60), toxicity.fit_texts([(t, y) for _, t, y in rows], rounds=60)
    assert a.weights.keys() == b.weights.keys() and a.bias == pytest.approx(b.bias)
    assert all(a.weights[f] == pytest.approx(b.weights[f], abs=1e-6) for f in a.weights)
    assert any(f.startswith("vil") for f in a.weights)


def slow_toxicity(model, text):
    """Noisy-or, sentence by sentence and word by word."""
    clean, any_ = 1.0, False
    for s in re.split(r"[.!?\n]+", text or ""):
        words = set(re.findall(r"[^\W\d_]+", s.lower()))
        if words:
            any_ = True
            z = model.bias + sum(model.weights.get(f, 0.0) for w in words for f in [w + "$", *[w[:n] for n in toxicity.PREFIXES if len(w) >= n]])
            clean *= 1 - 1 / (1 + np.exp(-z))
    return 1 - clean if any_ else 0.0


def test_toxicity_scores_and_gradient_by_brute_force(spark, local):
    texts = [(r.text, int("the" in (r.text or "").lower().split())) for r in list(local.values())[:120]]
    model = toxicity.fit_texts([(t or "", y) for t, y in texts], rounds=30)
    d = docs_of(spark, [(i, t) for i, (t, _) in enumerate(texts)] + ODD)
    got = toxicity.score_toxicity(d, model).collect()
    want = sorted(round(slow_toxicity(model, r.text), 9) for r in d.collect())
    assert sorted(round(r.score, 9) for r in got) == pytest.approx(want, abs=1e-8)


def test_held_out_toxicity(spark, sf):
    big = sf.replace("0.001", "0.1")
    got = queries.op2_toxicity(spark, big).join(table(spark, big, "labels"), "doc_id").where("held_out").select("predicted", "toxic").collect()
    assert np.mean([r.predicted for r in got if r.toxic == 1]) >= 0.9
    assert np.mean([r.predicted for r in got if r.toxic == 0]) <= 0.01


def test_scores_cover_odd_rows(spark):
    d = docs_of(spark, ODD).withColumn("predicted", F.lit("clash"))
    model = toxicity.SentenceModel({"word$": 9.0}, -5.0)
    a = toxicity.score_toxicity(d, model).collect()
    forest = quality.fit_forest(np.zeros((0, len(quality.FEATURES))), np.zeros(0))
    b = quality.score_quality(d, forest).collect()
    assert len(a) == len(b) == len(ODD)
    assert all(0 <= r.score <= 1 and r.predicted in (0, 1) for r in a + b)
    assert next(r for r in a if r.doc_id == 4).predicted == 1 and next(r for r in a if r.doc_id == 1).score == 0.0
    assert {r.held_out for r in a if r.doc_id is None} == {False}
    assert toxicity.score_toxicity(d.limit(0), model).count() == 0


def test_quality_forest_equals_plain_walk_and_beats_chance(local, spark, sf):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(900, len(quality.FEATURES)))
    y = ((x[:, 0] > 0.3) ^ (x[:, 4] > 0)).astype(float)
    f = quality.fit_forest(x[:600], y[:600])

    def walk(row):
        total = f.base
        for t in range(len(f.feature)):
            j = 0
            while f.left[t, j]:
                j = f.left[t, j] + int(row[f.feature[t, j]] > f.cut[t, j])
            total += f.value[t, j]
        return total

    assert np.allclose(f.margin(x[600:650]), [walk(r) for r in x[600:650]])
    assert ((f.score(x[600:]) >= 0.5) == y[600:]).mean() > 0.85
    s = quality.statistics(["", "A bc 12.\nA bc 12.\n"])
    assert not s[0].any() and s[1][quality.FEATURES.index("distinct_lines")] == 0.5


def test_held_out_quality(spark, sf):
    big = sf.replace("0.001", "0.01")
    got = queries.op3_quality(spark, big).join(table(spark, big, "labels"), "doc_id").where("held_out").collect()
    assert np.mean([r.predicted == r.quality for r in got]) > 0.9


# 4


def test_mixing_follows_the_weights(spark):
    rows = [(i, ["a", "b", None, "c"][0 if i % 3 == 0 else 1 + i % 3]) for i in range(4000)]
    d = spark.createDataFrame(rows, "doc_id long, source string")
    weights = {"a": 5, "b": 3, "c": 2, None: 1}
    got = mixing.mix_positions(d, weights, block_rows=10, bucket_rows=100).collect()
    assert sorted(r.doc_id for r in got) == list(range(4000))
    units = {s: weights.get(s, 1) for s in {r.source for r in got}}
    whole = sum(units.values())
    blocks = {}
    for r in got:
        assert r.release <= r.slot < r.deadline
        blocks.setdefault((r.source, r.block), set()).add(r.slot)
    assert all(len(s) == 1 for s in blocks.values())
    slots = {next(iter(s)): k[0] for k, s in blocks.items()}
    assert len(slots) == len(blocks)
    ends = {s: max(next(iter(x)) for k, x in blocks.items() if k[0] == s) for s in units}
    given = dict.fromkeys(units, 0)
    for t in range(min(ends.values()) + 1):
        given[slots[t]] += 1
        assert all(abs(given[s] - (t + 1) * u / whole) < 1 for s, u in units.items())
    same = mixing.mix_positions(d.repartition(5), weights, block_rows=10, bucket_rows=5000)
    assert sorted(map(tuple, same.collect()), key=str) == sorted(map(tuple, got), key=str)


def test_period_is_a_fair_schedule():
    for units in ([1], [3, 1], [7, 5, 1, 1], [1] * 9, [100, 37, 2]):
        plan = mixing.period(units)
        assert sorted(t for *_, t in plan) == list(range(sum(units)))
        assert all(i * sum(units) // units[s] <= t < -(-(i + 1) * sum(units) // units[s]) for s, i, t in plan)


def test_mixing_empty_and_order(spark):
    empty = spark.createDataFrame([], "doc_id long, source string, text string")
    assert mixing.mix_positions(empty).count() == 0
    d = spark.createDataFrame([(i, "ab"[i % 2], None) for i in range(300)], "doc_id long, source string, text string").withColumn("block", F.lit(1))
    out = mixing.mixed(d)
    assert out.columns == d.columns and sorted(r.doc_id for r in out.collect()) == list(range(300))


CLASHES = ["block", "slot", "release", "deadline", "place", "s_", "id_", "t_", "row_", "h_", "k_", "r_", "n_", "part_", "u_", "before_"]


def test_mixing_with_clashing_columns(spark):
    rows = [(i, "abc"[i % 3], f"keep {i}") for i in range(600)]
    d = spark.createDataFrame(rows, "doc_id long, source string, text string")
    clash = d
    for c in CLASHES:
        clash = clash.withColumn(c, F.concat(F.lit(c), F.col("doc_id").cast("string")))
    key = ["doc_id", *mixing.ADDED]
    got = mixing.mix_positions(clash, block_rows=10)
    assert sorted(got.columns) == sorted(set(clash.columns) | set(mixing.ADDED)) and len(set(got.columns)) == len(got.columns)
    assert sorted(map(tuple, got.select(key).collect())) == sorted(map(tuple, mixing.mix_positions(d, block_rows=10).select(key).collect()))
    assert all(r.h_ == f"h_{r.doc_id}" and r.part_ == f"part_{r.doc_id}" and r.text == f"keep {r.doc_id}" for r in got.collect())
    out = mixing.mixed(clash)
    assert out.columns == clash.columns
    assert sorted(map(tuple, out.collect())) == sorted(map(tuple, clash.collect()))


def test_mixing_of_repeated_ids_and_rows(spark):
    rows = [(5, "a", f"t{i}") for i in range(900)] + [(None, "a", "x")] * 700 + [(5, "a", "same")] * 600 + [(i, "b", None) for i in range(500)] + [(9, None, "")] * 3
    d = spark.createDataFrame(rows, "doc_id long, source string, text string")
    got = mixing.mix_positions(d, {"a": 3, "b": 2}, block_rows=10, bucket_rows=20).collect()
    assert sorted(map(str, ((r.doc_id, r.source, r.text) for r in got))) == sorted(map(str, rows))
    assert len({(r.slot, r.place) for r in got}) == len(rows)
    for s in ("a", "b", None):
        at = sorted((r.block, r.place) for r in got if r.source == s)
        assert at == [(n // 10, n % 10) for n in range(len(at))]


def test_mixing_keeps_ties_together_by_hash_of_the_row(spark):
    rows = [(i // 4, "a", f"t{i % 2}") for i in range(400)]
    d = spark.createDataFrame(rows, "doc_id long, source string, text string")
    key = lambda df: sorted((r.slot, r.place, r.doc_id, r.text) for r in df.collect())
    assert key(mixing.mix_positions(d)) == key(mixing.mix_positions(d.orderBy(F.rand(3)).repartition(7)))


def test_mixing_refuses_what_it_cannot_plan(spark):
    d = spark.createDataFrame([(1, "a", "")], "doc_id long, source string, text string")
    for w in ({"a": 0}, {"a": mixing.MOST_SLOTS + 1}):
        with pytest.raises(ValueError):
            mixing.mix_positions(d, w)


# 5


def slow_simhash(text, n=3):
    import xxhash

    words = [w for w in re.split(r"[\x20\x09-\x0d]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text)) if w]
    sh = [" ".join(words[i : i + n]) for i in range(len(words) - n + 1)] or ([" ".join(words)] if words else [])
    hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def slow_components(items):
    root = list(range(len(items)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(items)):
        for j in range(i):
            if bin(items[i] ^ items[j]).count("1") <= 3:
                root[find(i)] = find(j)
    return [find(i) for i in range(len(items))]


def test_simhash_against_brute_force(spark, docs, local):
    got = {r.doc_id: r for r in simhash.simhash_components(docs).collect()}
    ids = sorted(local)
    fps = [slow_simhash(local[i].text) for i in ids]
    assert [got[i].fingerprint for i in ids] == [f"{f:016x}" for f in fps]
    comp = slow_components(fps)
    least = {}
    for i, c in zip(ids, comp):
        least[c] = min(least.get(c, i), i)
    assert [got[i].component_id for i in ids] == [least[c] for c in comp]


def test_close_links_lose_none(spark):
    rng = np.random.default_rng(8)
    base = [int(x) for x in rng.integers(0, 1 << 63, 60)]
    codes = set(base)
    for b in base:
        for _ in range(6):
            x = b
            for bit in rng.choice(64, int(rng.integers(1, 6)), replace=False):
                x ^= 1 << int(bit)
            codes.add(x)
    codes = sorted(codes)
    signed = [c - (1 << 64) if c >> 63 else c for c in codes]
    links = simhash.close_links(spark.createDataFrame([(c,) for c in signed], "fp long"))
    root = {r.node: r.root for r in components.connected_components(links, "a", "b").collect()}
    got = [root.get(c, c) for c in signed]
    want = slow_components(codes)
    assert len({(g, w) for g, w in zip(got, want)}) == len(set(got)) == len(set(want))


def test_simhash_odd_rows(spark):
    got = simhash.simhash_components(docs_of(spark, ODD)).collect()
    assert len(got) == len(ODD)
    by = {r.doc_id: r for r in got}
    assert by[1].fingerprint == by[2].fingerprint == by[3].fingerprint == "0" * 16 and by[3].component_id == 1
    assert by[7].component_id == 5 and by[None].component_id is None
    assert simhash.simhash_components(docs_of(spark, [])).count() == 0


def test_groups_of_similar_texts(spark):
    rng = np.random.default_rng(3)
    vocabulary = [f"w{i}" for i in range(3000)]
    rows, want = [], {}
    for g in range(40):
        words = list(rng.choice(vocabulary, 300))
        rows.append((10 * g, " ".join(words)))
        for k in range(1, 4):
            copy = list(words)
            for at in rng.choice(300, k * 2, replace=False):
                copy[at] = "x" + str(rng.integers(0, 10**6))
            rows.append((10 * g + k, " ".join(copy)))
        rows.append((10 * g + 4, " ".join(words).upper()))
    d = docs_of(spark, rows).withColumn("component_id", F.lit("clash"))
    got = {r.doc_id: r.component_id for r in simhash.similar_groups(d.select("doc_id", "text")).collect()}
    sh = {i: {tuple(w[k : k + 5]) for k in range(len(w) - 4)} for i, w in ((i, t.lower().split()) for i, t in rows)}
    alike = [(a, b) for a in sh for b in sh if a < b and a // 10 == b // 10 and len(sh[a] & sh[b]) >= 0.8 * len(sh[a] | sh[b])]
    assert np.mean([got[a] == got[b] for a, b in alike]) > 0.97 and all(got[i] // 10 == i // 10 for i in got)
    kept = simhash.keep_one_of_each(d)
    assert kept.columns == d.columns and kept.count() == len(set(got.values()))
    assert simhash.keep_one_of_each(docs_of(spark, [(None, "a b"), (None, "a b"), (3, None)])).count() == 3


def test_components_of_a_long_chain(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(0, 60)] + [(100, 101), (101, 100)], "a long, b long")
    got = {r.node: r.root for r in components.connected_components(links, "a", "b").collect()}
    assert got == {i: 0 for i in range(1, 61)} | {101: 100}


def test_workers_give_memory_back(monkeypatch):
    import pyarrow as pa

    given = []
    monkeypatch.setattr(pa, "default_memory_pool", lambda: type("Pool", (), {"release_unused": lambda self: given.append(1)})())
    batches = [pa.record_batch({"a": [n, n + 1]}) for n in range(3)]
    assert list(lean(lambda each: (b.slice(1) for b in each))(iter(batches))) == [b.slice(1) for b in batches]
    assert len(given) == 4


def test_components_of_few_links_need_few_jobs(spark, monkeypatch):
    """Links that a task can hold are solved in one; the same roots come from the steps by joins, which many links take."""
    rng, root = np.random.default_rng(31), {}
    nodes = np.concatenate([[-(1 << 63), (1 << 63) - 1], rng.integers(-(1 << 62), 1 << 62, 398)]).tolist()
    pairs = [(nodes[i], nodes[j]) for i, j in rng.integers(0, 400, (230, 2))] + [(nodes[0], n) for n in nodes[350:]] + [(5, 5), (None, 7), (7, None)]

    def find(i):
        return i if root.setdefault(i, i) == i else find(root[i])

    for a, b in pairs:
        if a is not None and b is not None:
            a, b = sorted((find(a), find(b)))
            root[b] = a
    want = {i: find(i) for i in root if find(i) != i}
    links, sc = spark.createDataFrame(pairs, "a long, b long"), spark.sparkContext
    sc.setJobGroup("few-links", "")
    try:
        rows = components.connected_components(links, "a", "b").collect()
    finally:
        sc._jsc.clearJobGroup()
    assert len(sc.statusTracker().getJobIdsForGroup("few-links")) <= 8
    assert len(rows) == len(want) and {r.node: r.root for r in rows} == want
    none = links.where("a = b")
    assert components.connected_components(none, "a", "b").columns == ["node", "root"] and not components.connected_components(none, "a", "b").count()
    monkeypatch.setattr(components, "MOST_IN_A_TASK", 0)
    assert {r.node: r.root for r in components.connected_components(links, "a", "b").collect()} == want


# 6


PII_TEXTS = [
    (1, "Mail anna.b42@mail8.example.com or ANNA.b42@mail8.example.com, call +1 (988) 555-2485 or +1 988 555 2485 or +19885552485."),
    (2, "Card 4041894974608795, again 4041-8949-7460-8795; host 42.144.35.254."),
    (3, "Frau Meier and Mr. John Smith met Mr. John Smith; господин Иванов came with госпожа Иванова."),
    (4, None), (5, ""), (6, "no data at all"), (1, "Mail anna.b42@mail8.example.com"), (None, "from 42.144.35.254"), (None, "from 42.144.35.254"), (7, "ssn 123-45-6789, version 3.11.2.1"),
    (8, "Mr Smith, Mr. Smith, Mrs Smith's and Mr John Paul Smith. Mr McDonald, Mrs O'Brien, Frau Mueller-Schmidt, Herr Dr. Ludwig van der Berg, Mr J. Doe, Mr Smith Mr Jones"),
    (9, "IBAN DE89 3704 0044 0532 0130 00 or DE89370400440532013000, GB82WEST12345698765432"),
    (10, "odd \x01 marks \x02 and \x02\x03 a@x.org\x01b@x.org $1 \\1"),
    (11, "word " * 40_000 + "+49 30 901820 1234 +44 20 7946 0958"),
]


def test_pii_surrogates(spark):
    d = docs_of(spark, PII_TEXTS).withColumn("row", F.lit("clash")).withColumn("parts", F.lit(1)).withColumn("kind", F.lit("x"))
    got = pii.replace_personal_data(d, "key").collect()
    assert len(got) == len(PII_TEXTS)
    by = {r.doc_id: r for r in got if r.doc_id not in (1, None)}
    one = sorted((r.text for r in got if r.doc_id == 1), key=len)[-1]
    everything = " ".join(r.text or "" for r in got)
    for secret in ("anna.b42", "555-2485", "4041894974608795", "42.144.35.254", "Meier", "Smith", "Иванов", "123-45-6789", "Donald", "Brien", "Mueller", "Schmidt", "Berg", "Doe", "Jones", "Paul", "3704", "WEST", "a@x", "7946"):
        assert secret not in everything, secret
    mails = re.findall(r"\S+@[\w.]+\w", one)
    assert mails[0] == mails[1].lower() and mails[1][:4].isupper() and re.fullmatch(r"[a-z]{4}\.[a-z]\d\d@[a-z]{4}\d\.[a-z]{7}\.com", mails[0])
    phones = re.findall(r"\+1[ \d()-]+\d", one)
    assert len(phones) == 3 and len({re.sub(r"\D", "", p) for p in phones}) == 1 and re.fullmatch(r"\+1 \(\d{3}\) \d{3}-\d{4}", phones[0])
    card = re.search(r"\d{16}", by[2].text)[0]
    digits = [int(c) for c in reversed(card)]
    assert sum(d if k % 2 == 0 else sum(divmod(2 * d, 10)) for k, d in enumerate(digits)) % 10 == 0 and card[0] == "4"
    assert card in by[2].text.replace("-", "").replace(card, "", 1)
    assert len(set(re.findall(r"Mr\. \w+ \w+", by[3].text))) == 1
    he, she = re.search(r"господин ([а-яА-Я]+) .*госпожа ([а-яА-Я]+)", by[3].text).groups()
    assert she == he + "а"
    family = re.match(r"Mr (\w+), Mr\. (\w+), Mrs (\w+)'s and Mr (\w+) (\w+) (\w+)\. Mr (\w+), Mrs (\w+), Frau (\w+-\w+), Herr Dr\. (\w+) van der (\w+), Mr [A-Z]\. (\w+), Mr (\w+) Mr (\w+)$", by[8].text).groups()
    assert family[0] == family[1] == family[2] == family[5] == family[12] == by[3].text.split(";")[0].split()[-1]
    assert len({family[0], *family[6:9], *family[10:12], family[13]}) == 7
    for account in re.findall(r"[A-Z]{2}\d\d[A-Z0-9 ]{12,}", by[9].text):
        a = account.replace(" ", "")
        assert int("".join(str(int(c, 36)) for c in a[4:] + a[:4])) % 97 == 1
    assert re.match(r"IBAN (DE[\d ]+) or (DE\d+),", by[9].text) and by[9].text[5:32].replace(" ", "") == by[9].text[36:58]
    assert re.fullmatch("odd \x01 marks \x02 and \x02\x03 [a-z]+@[a-z]\\.org\x01[a-z]+@[a-z]\\.org \\$1 \\\\1", by[10].text)
    assert by[4].text is None and by[4].n_entities == 0 and by[5].text == "" and by[6].text == "no data at all" and by[8].n_entities == 11
    assert {r.text.split()[1] for r in got if r.doc_id is None} == {by[2].text.rstrip(".").split()[-1]}
    assert pii.replace_personal_data(docs_of(spark, []), "key").count() == 0


def slow_kind(v):
    import regex

    if "@" in v:
        return "email"
    return next((k for k, p in (("ip", pii.IPV4), ("iban", pii.IBAN), ("ssn", pii.SSN), ("card", pii.CARD), ("phone", pii.PHONE)) if regex.search(f"^(?:{p})$", v)), "name")


def slow_units(v):
    kind, bare = slow_kind(v), re.sub("[^0-9A-Za-z]", "", v)
    if kind != "name":
        return [(kind, {"email": v.lower(), "phone": ("+" if v[0] == "+" else "") + bare, "iban": bare.upper(), "ip": v}.get(kind, bare), v)]
    words, out = v.split(" "), []
    bare_words = {w.rstrip(".") for w in words}
    gender = "f" if bare_words & set(pii.FEMALE_TITLES) else "m" if bare_words & set(pii.MALE_TITLES) else "n"
    for i, w in enumerate(words):
        script = "c" if "Ѐ" <= w[0] <= "ӿ" else "l"
        if i == len(words) - 1:
            out.append((f"family_{script}", w[:-1] if gender == "f" and script == "c" and w.endswith("а") else w, w))
        elif w.rstrip(".") in pii.MALE_TITLES + pii.FEMALE_TITLES + pii.NEUTRAL_TITLES or w in pii.PARTICLES:
            out.append(("keep", w, w))
        else:
            out.append((f"given_{gender}_{script}", w, w))
    return out


def slow_surrogate(key, kind, canon, attempt):
    stream = lambda *parts: bytes.fromhex("".join(hashlib.sha256("|".join([key, str(k), *parts]).encode()).hexdigest() for k in range(4)))
    h, more, cyrillic = stream(kind, canon, str(attempt)), min(attempt // 3, 40), kind.endswith("_c")
    syl = lambda first, n, c=cyrillic: "".join((pii.CYRILLIC_SYLLABLES if c else pii.LATIN_SYLLABLES)[h[(i + first) % 128] % 24] for i in range(1, n + 1))

    def drawn(form, h, skip=0):
        pick = lambda c, b: chr(48 + b % 10) if c.isdigit() else chr(97 + b % 26) if c.islower() else chr(65 + b % 26)
        return "".join(c if i < skip or not (c.isascii() and c.isalnum()) else pick(c, h[i % 128]) for i, c in enumerate(form))

    if kind == "email":
        local, domain = canon.split("@")
        top = domain[domain.rindex("."):]
        return drawn(local, h) + syl(60, more, False) + "@" + drawn(domain[: -len(top)], stream("domain", domain)) + top
    if kind == "ip":
        return ".".join([str(h[0] % 223 + 1), *[str(h[k] % 254 + 1) for k in (1, 2, 3)]])
    if kind == "card":
        d = drawn(canon, h, 1)
        total = sum(sum(divmod(int(c) * 2, 10)) if k % 2 == 0 else int(c) for k, c in enumerate(reversed(d[:-1])))
        return d[:-1] + str(-total % 10)
    if kind == "iban":
        d = drawn(canon, h, 2)
        return d[:2] + f"{98 - int(''.join(str(int(c, 36)) for c in d[4:] + d[:2] + '00')) % 97:02d}" + d[4:]
    if kind == "phone":
        return drawn(canon, h, 0 if canon[0] != "+" else 2 if canon[1] in pii.CODES_OF_ONE else 3 if canon[1:3] in pii.CODES_OF_TWO else 4)
    if kind == "ssn":
        return drawn(canon, h)
    if kind.startswith("family"):
        return syl(0, 3 + more).capitalize() + ("-" + syl(50, 3 + more).capitalize() if "-" in canon else "")
    if canon.endswith("."):
        return syl(1, 1)[0].upper() + "."
    f, m = (pii.CYRILLIC_FEMALE, pii.CYRILLIC_MALE) if cyrillic else (pii.LATIN_FEMALE, pii.LATIN_MALE)
    pool = {"f": f, "m": m, "n": f + m}[kind[6]]
    return pool[h[0] % len(pool)] + syl(1, min(attempt, 40))


def slow_replace(texts, key):
    """Every text in turn, forms settled one attempt after the other."""
    import regex

    found = [list(regex.finditer(pii.ENTITY, t or "")) for t in texts]
    known = {u[:2] for ms in found for m in ms for u in slow_units(m.group()) if u[0] != "keep"}
    sur, open_, attempt = {}, set(known), 0
    while open_:
        draw = {x: slow_surrogate(key, *x, attempt) for x in open_}
        owner = {}
        for (k, c), s in draw.items():
            owner[k, s] = min(owner.get((k, s), c), c)
        taken = known | {(k, s) for (k, _), s in sur.items()}
        fine = {x: s for x, s in draw.items() if owner[x[0], s] == x[1] and (x[0], s) not in taken}
        sur, open_, attempt = sur | fine, open_ - set(fine), attempt + 1

    def written_out(kind, canon, v):
        if kind == "keep":
            return v
        s = sur[kind, canon]
        if kind in pii.NUMBERS:
            it = iter(s.lstrip("+"))
            fill = lambda c: next(it).lower() if c.islower() else next(it)
            return "".join(fill(c) if c.isascii() and c.isalnum() else c for c in v)
        if kind == "email":
            return "".join(x.upper() if c.isupper() else x for x, c in zip(s, v)) if len(s) == len(v) else s
        return s + "а" if kind.startswith("family") and len(v) > len(canon) else s

    out = []
    for t, ms in zip(texts, found):
        for m in reversed(ms):
            t = t[: m.start()] + " ".join(written_out(*u) for u in slow_units(m.group())) + t[m.end():]
        out.append((t, len(ms)))
    return out


def test_pii_against_brute_force(spark, docs):
    rows = PII_TEXTS + [(r.doc_id + 1000, r.text) for r in docs.collect()]
    rows += [(5000 + i, f"Mr Name{chr(97 + i // 26)}{chr(97 + i % 26)} or Mrs Kim Lee; {chr(97 + i % 26)}@x.org 10.0.{i // 200}.{i % 200} Ms {chr(65 + i % 26)}a Ko") for i in range(400)]
    got = pii.replace_personal_data(docs_of(spark, rows), "k").collect()
    want = slow_replace([t for _, t in rows], "k")
    assert sorted(map(str, got)) == sorted(f"Row(doc_id={i!r}, text={t!r}, n_entities={n})" for (i, _), (t, n) in zip(rows, want))


def test_pii_keeps_forms_apart(spark):
    rows = [(i, [f"Mr Name{chr(97 + i // 26)}{chr(97 + i % 26)} {chr(97 + i % 20)}@x.org 10.0.{i // 200}.{i % 200}", "x"]) for i in range(400)]
    cut = docs_of(spark, [(i, t[0]) for i, t in rows]).select(F.col("doc_id").alias("row"), pii.cut_texts(F.col("text")).alias("parts"))
    entities = pii.find_entities(cut)
    got = pii.assign_surrogates(entities, "k").collect()
    assert len({(r.kind, r.sur) for r in got}) == len(got) == entities.where("kind <> 'keep'").select("kind", "canon").distinct().count() == 820
    assert not {(r.kind, r.sur) for r in got} & {(r.kind, r.canon) for r in got}


# 7


def test_language(spark, sf):
    big = sf.replace("0.001", "0.01")
    got = queries.op7_language(spark, big).join(table(spark, big, "documents").select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r.lang == r.lang_pred for r in got]) > 0.95
    odd = language_id.identify_language(docs_of(spark, ODD + [(8, "123 !!")]), {"en": b" the word and of ", "fr": b" le mot et de "}).collect()
    by = {r.doc_id: r for r in odd}
    assert by[1].lang_pred == by[2].lang_pred == by[8].lang_pred == "und" and by[8].score == 0.0
    assert by[4].lang_pred in ("en", "fr") and len(odd) == len(ODD) + 1
    assert {r.lang_pred for r in language_id.identify_language(docs_of(spark, ODD), {}).collect()} == {"und"}


def slow_language(dicts, text):
    """A new compressor for each block and language."""
    import zstandard

    sizes = {}
    for name, data in dicts.items():
        p = zstandard.ZstdCompressionParameters(write_content_size=False, write_checksum=False, write_dict_id=False, **language_id.PARAMETERS)
        d = zstandard.ZstdCompressionDict(data, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        t = " " + " ".join(re.findall(r"[^\W\d_]+", text.lower())) + " "
        sizes[name] = sum(len(zstandard.ZstdCompressor(compression_params=p, dict_data=d).compress(t[i : i + language_id.BLOCK_CHARS].encode())) for i in range(0, len(t), language_id.BLOCK_CHARS))
    best = sorted(sizes.items(), key=lambda x: (x[1], x[0]))
    return best[0][0], (best[1][1] - best[0][1]) / best[1][1]


def test_language_against_brute_force(spark, docs, local):
    clash = docs.withColumn("h", F.lit("clash")).withColumn("part", F.lit(1)).withColumn("r", F.lit(1)).withColumn("score", F.lit("x"))
    dicts = language_id.fit_dictionaries(clash)
    assert len(dicts) == 4 and all(0 < len(v) <= language_id.DICT_BYTES for v in dicts.values())
    got = {r.doc_id: r for r in language_id.identify_language(clash, dicts).collect()}
    for i in sorted(local)[:60]:
        if any(map(str.isalpha, local[i].text or "")):
            name, margin = slow_language(dicts, local[i].text)
            assert got[i].lang_pred == name and got[i].score == pytest.approx(margin / (margin + language_id.REJECT_MARGIN) if margin else 0.0)


def test_dictionaries_of_hot_and_of_many_languages(spark):
    rows = [(1, "aa", "one text only " * 30)] * 3000 + [(i, "bb", f"word{i} and more") for i in range(3000)] + [(i, f"l{i}", f"tongue {i}") for i in range(30)]
    d = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    dicts = language_id.fit_dictionaries(d, sample_docs=10, dict_bytes=400)
    assert {"aa", "bb"} <= set(dicts) and len(dicts) > 20 and all(len(v) <= 400 for v in dicts.values())
    assert len(re.findall("word", dicts["bb"].decode())) == 10
    assert language_id.fit_dictionaries(d.limit(0)) == {}


# 8


def slow_secrets(text):
    text = text or ""
    out = []
    kinds = {
        "assign": r"""([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""",
        "access": r"AKIA[A-Z0-9]+",
        "hex": r"[0-9a-f]+",
    }
    for k, (kind, p) in enumerate(kinds.items()):
        for m in re.finditer(p, text):
            if len(m.group(2) if kind == "assign" else m.group()) >= {"assign": 8, "access": 16, "hex": 32}[kind]:
                out.append((m.start(), k, kind, m.end()))
    out.sort()
    counts = [sum(o[2] == kind for o in out) for kind in kinds]
    return counts, hashlib.sha256(",".join(f"{k}:{a}:{b}" for a, _, k, b in out).encode()).hexdigest()


def test_secrets_against_brute_force(spark, docs):
    rng = np.random.default_rng(6)
    bits = ["password", "PassWd", "SECRET", "toKen", "api_key", "apikey", " ", "=", ":", '"', "'", "abcdef12", "AKIA", "ABCDEFGH12345678", "0123456789abcdef", "0123456789abcdef", "zz", "ſecret", "é", "\n", "ghp_" + "a1" * 18]
    rows = [(i, "".join(rng.choice(bits, int(rng.integers(0, 14))))) for i in range(1500)] + ODD
    rows += [(r.doc_id + 10_000, r.text) for r in docs.collect()]
    got = secrets.find_secrets(docs_of(spark, rows)).collect()
    want = sorted((i if i is not None else -1, *slow_secrets(t)[0], slow_secrets(t)[1]) for i, t in rows)
    assert sorted((r.doc_id if r.doc_id is not None else -1, r.n_assign, r.n_access, r.n_hex, r.base_sha256) for r in got) == want
    assert any("github:" in r.spans for r in got)


def test_secrets_with_clashing_columns_and_empty_table(spark):
    d = docs_of(spark, ODD + [(8, "token = abcdef123456")])
    clash = d.withColumn("n_assign", F.lit("clash")).withColumn("spans", F.lit(1)).withColumn("base_sha256", F.lit(None).cast("string"))
    assert sorted(map(str, secrets.find_secrets(clash).collect())) == sorted(map(str, secrets.find_secrets(d).collect()))
    assert secrets.find_secrets(d.limit(0)).count() == 0


def test_trigram_queries():
    assert secrets.trigram_query(r"[0-9a-f]+") == secrets.ANY
    assert secrets.trigrams_of(secrets.trigram_query(r"AKIA[A-Z0-9]+")) == {"aki", "kia"}
    q = secrets.trigram_query(secrets.BASE_RULES[0][1])
    assert {"pas", "swd", "tok", "key", "api"} <= secrets.trigrams_of(q)
    assert secrets.trigram_query(r"(?:ab)?cdef") != secrets.ANY and secrets.trigram_query("x.*y") == secrets.ANY


# 9


def slow_distance(p, t):
    row = [0] * (len(t) + 1)
    for i, c in enumerate(p, 1):
        new = [i]
        for j, x in enumerate(t, 1):
            new.append(min(row[j] + 1, new[-1] + 1, row[j - 1] + (c != x)))
        row = new
    return min(row)


def test_decontamination_against_brute_force(spark):
    rng = np.random.default_rng(7)
    letters = list("abcdefgh ij")
    text = lambda n: "".join(rng.choice(letters, n))
    items = [(i, text(int(rng.integers(30, 140)))) for i in range(8)] + [(50, ""), (51, None), (52, "zq!"), (0, "second text of item zero, long enough")]
    rows = list(ODD)
    for i in range(120):
        p = list(items[int(rng.integers(0, 8))][1])
        for _ in range(int(rng.integers(0, max(1, len(p) // 7)))):
            at, kind = int(rng.integers(0, len(p))), rng.integers(0, 3)
            p[at : at + 1] = [] if kind == 0 else [p[at], "z"] if kind == 1 else ["Y"]
        body = "".join(p)
        rows.append((100 + i, text(int(rng.integers(0, 90))) + (body.upper() if i % 3 == 0 else body.replace(" ", "\n")) + text(int(rng.integers(0, 90)))))
    rows.append((900, "has zq! inside"))
    b = spark.createDataFrame(items, "item_id long, text string")
    got = {(r.doc_id, r.item_id): r.edits for r in decontaminate.contaminated_spans(docs_of(spark, rows), b).collect()}
    fold = lambda s: re.sub(r"\s", " ", s.lower())
    want = {}
    for i, t in rows:
        for k, p in items:
            if not p or not t or len(t) > 100_000:
                continue
            m = len(p)
            budget = max(0, min(int(decontaminate.RATE * m + 1e-9), (m - 8) // 8))
            d = slow_distance(fold(p), fold(t))
            if d <= budget:
                want[i, k] = min(d, want.get((i, k), d))
    assert got == want and len(want) > 50
    chunked = decontaminate.contaminated_spans(docs_of(spark, rows), b, chunk_chars=150)
    assert {(r.doc_id, r.item_id) for r in chunked.collect()} == set(want)
    kept = decontaminate.drop_contaminated(docs_of(spark, rows).withColumn("edits", F.lit(1)), b)
    assert sorted(str(r.doc_id) for r in kept.collect()) == sorted(str(i) for i, _ in rows if not any(w[0] == i for w in want))
    assert decontaminate.contaminated_spans(docs_of(spark, rows), b.limit(0)).count() == 0


def slow_spans(p, t, budget):
    """(edits, start, end) of the occurrences with fewest edits, by a table that carries starts; None over the budget."""
    row = [(0, j) for j in range(len(t) + 1)]
    for i, c in enumerate(p, 1):
        new = [(i, 0)]
        for j, x in enumerate(t, 1):
            new.append(min((row[j][0] + 1, row[j][1]), (new[-1][0] + 1, new[-1][1]), (row[j - 1][0] + (c != x), row[j - 1][1])))
        row = new
    least = min(d for d, _ in row)
    return {(s, j) for j, (d, s) in enumerate(row) if d == least} if least <= budget else None


def test_decontamination_spans_and_long_texts(spark):
    rng = np.random.default_rng(17)
    text = lambda n: "".join(rng.choice(list("abcdefghijk "), n))
    items = [(i, text(int(rng.integers(60, 200)))) for i in range(5)]
    rows, want = [], {}
    for i in range(40):
        k = i % 5
        p = list(items[k][1])
        for _ in range(i % 4):
            p[int(rng.integers(0, len(p)))] = "z"
        before = text(200_000 if i in (3, 4) else int(rng.integers(0, 80)))
        rows.append((i, before + "".join(p) + text(int(rng.integers(0, 80)))))
        want[i, k] = (len(before), len(before) + len(p), sum(a != b for a, b in zip(p, items[k][1])))
    clash = docs_of(spark, rows).withColumn("start", F.lit("clash")).withColumn("item_id", F.lit(1))
    got = {(r.doc_id, r.item_id): (r.start, r.end, r.edits) for r in decontaminate.contaminated_spans(clash, spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert got.keys() == want.keys()
    for key, (a, b, d) in got.items():
        assert d == want[key][2] and abs(a - want[key][0]) <= d and abs(b - want[key][1]) <= d
        if d == 0:
            assert (a, b) == want[key][:2]
        t = dict(rows)[key[0]]
        lo = max(0, a - 300)
        assert (a - lo, b - lo) in slow_spans(dict(items)[key[1]], t[lo : b + 300], 20)


# 10


def test_packing_round_trip():
    rng = np.random.default_rng(1)
    for bits in (1, 3, 8, 13, 16, 17, 32):
        ids = rng.integers(0, 1 << bits, 501, dtype=np.uint64).astype(np.uint32)
        raw = token_files.pack(ids, bits)
        assert len(raw) == (501 * bits + 7) // 8
        assert (token_files.unpack(raw, bits, 501) == ids).all()
        assert (token_files.unpack(raw, bits, 77, 123) == ids[123:200]).all()
    assert token_files.id_bits(50_257) == 16 and token_files.id_bits(32_000) == 15


def test_encoder_equals_the_library():
    from tokenizers import Tokenizer

    path = queries.tokenizer_path()
    whole = Tokenizer.from_file(path)
    rng = np.random.default_rng(2)
    bits = [" ", "  ", "\n", " \n", "\n ", "\t", "a", "Bc", "'s", "12", "²", "!", "é", "中", "<|endoftext|>", " x", "\r\n", "don't", "×", "÷", "Ж", "_", "\x00", "\x1c", "\x85", " ", "ɐ", "ﬁ", "😀", "̈", "the quick", "."]
    texts = ["".join(rng.choice(bits, int(rng.integers(0, 20)))) for _ in range(3000)]
    e = token_files.encoder(path)
    for at in range(0, len(texts), 250):
        part = texts[at : at + 250]
        assert e.raw_ids(part) == [np.array(x.ids, "<u4").tobytes() for x in whole.encode_batch(part, add_special_tokens=False)]


def test_encoder_tells_like_pieces_apart():
    from tokenizers import Tokenizer

    path = queries.tokenizer_path()
    whole, e = Tokenizer.from_file(path), token_files.Encoder(path)
    thue = "".join("ab"[bin(i).count("1") % 2] for i in range(4096))
    for n in (9, 16, 23, 24, 25, 64, 1024, 4096):  # a run of letters and its complement have equal polynomial hashes modulo 2^64
        texts = ["c" * 8 + thue[:n], "c" * 8 + thue[:n].translate(str.maketrans("ab", "ba")), "hi <|endoftext|> there", "<|endoftext|>" * 3]
        for _ in range(2):  # the second time from the store
            for part in (texts, texts[:1], texts[1:2]):
                assert e.raw_ids(part) == [np.array(x.ids, "<u4").tobytes() for x in whole.encode_batch(part, add_special_tokens=False)]
    assert whole.encode("hi <|endoftext|> there", add_special_tokens=False).ids == [5303, 220, 50256, 612]


def test_encoder_of_other_files_asks_the_library():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    texts = ["Some Words  here", "", "é 12 <|endoftext|>"]
    assert token_files.Encoder(path).raw_ids(texts) == [np.array(x.ids, "<u4").tobytes() for x in Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)]


def test_token_file_of_one_id(spark):
    rows = [(7, f"text {i % 50}") for i in range(2000)] + [(7, "same")] * 500 + [(None, "x")] * 500
    d = docs_of(spark, rows).withColumn("h_", F.lit("clash")).withColumn("n_", F.lit(1)).withColumn("shard", F.lit("clash"))
    blocks = token_files.write_token_file(d, queries.tokenizer_path(), shards=8)
    got = token_files.document_digests(blocks).orderBy("start").collect()
    assert len(got) == 3000 and [r.doc_id for r in got] == [None] * 500 + [7] * 2500
    assert all(a.start + a.n_tokens == b.start for a, b in zip(got, got[1:]))
    assert max(r["count"] for r in token_files.read_token_file(blocks).groupBy("shard").count().collect()) < 1000


def test_token_file_against_the_library(spark, docs, local):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(queries.tokenizer_path())
    blocks = token_files.write_token_file(docs, queries.tokenizer_path(), block_ids=5000, shards=3)
    got = {r.doc_id: r for r in token_files.document_digests(blocks).collect()}
    ids = {r.doc_id: r.ids for r in token_files.read_token_file(blocks, with_ids=True).collect()}
    start = 0
    for i in sorted(local):
        want = tok.encode(local[i].text, add_special_tokens=False).ids + [0]
        assert (got[i].start, got[i].n_tokens, got[i].ids_crc32) == (start, len(want), zlib.crc32(np.array(want, "<u4").tobytes())) and ids[i] == want
        start += len(want)
    assert blocks.count() > 3


def test_token_file_odd_rows(spark):
    blocks = token_files.write_token_file(docs_of(spark, ODD), queries.tokenizer_path())
    got = token_files.document_digests(blocks).orderBy("start").collect()
    assert len(got) == len(ODD) and got[0].start == 0 and got[0].doc_id is None
    assert all(a.start + a.n_tokens == b.start for a, b in zip(got, got[1:]))
    assert {r.n_tokens for r in got if r.doc_id in (1, 2)} == {1}
    assert token_files.document_digests(token_files.write_token_file(docs_of(spark, []), queries.tokenizer_path())).count() == 0


def test_training_rows_are_bounded_and_outside_the_fold(spark, sf, local):
    sample = labelled_documents(table(spark, sf, "documents"), table(spark, sf, "labels"), "quality", 5, 0, {0: 3, 1: 5}).collect()
    assert 0 < len(sample) <= 8
    assert all(zlib.crc32(str(r.doc_id).encode()) % 5 and r.text == local[r.doc_id].text for r in sample)


def test_training_holds_a_bounded_number_of_words(spark, monkeypatch):
    monkeypatch.setattr(toxicity, "TRAIN_ITEMS", 40)
    d = spark.createDataFrame([(i, "vile bad words. " * (1000 if i == 3 else 1) if i % 2 else "calm good words here.", i % 2) for i in range(40)], "doc_id long, text string, y int")
    assert toxicity.fit_toxicity(d, rounds=20).document("vile bad words")[0] > toxicity.fit_toxicity(d, rounds=20).document("calm good words")[0]
