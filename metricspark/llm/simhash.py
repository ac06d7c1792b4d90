"""SimHash near-duplicates by meet-in-the-middle ball hashing.

Links within `radius` bits are found without comparing all pairs: every fingerprint emits the codes within half
the radius of it, codes are shuffled, and fingerprints that meet at a code are candidates, verified by their
distance. Equal fingerprints are collapsed first, so a code is met by a bounded number of distinct fingerprints
(those within the half radius of it), however many copies there are: no bucket grows with the data.

Radius 3 does not halve evenly: two fingerprints at distance 3 meet at a code 1 away from one and 2 away from the
other. They have opposite parity, so only odd ones need to emit codes 2 away; and of the three differing bits some
two lie within 21 places of each other on the circle of 64, so only such pairs of bits are flipped. At a code, each
fingerprint is linked to the smallest one that is at most 1 away from it: any two of these are within 3 bits, and
no link is lost (see `close_links`).

Before the balls, a cheap pass drops fingerprints that cannot have a partner: within 3 bits, one 32-bit half
differs in at most one bit; each half emits its own code, odd halves their 1-bit neighbours as well, and only
fingerprints that share such a code with another one go on.

That pass bites while distinct fingerprints are far fewer than 2^32 / 33: beyond some 10^8 of them nearly all halves meet by chance, and every odd
fingerprint emits 1408 codes. The result stays right; the work is then 700 codes a fingerprint instead of a few.

Null texts are empty; their fingerprint is zero and links like any other. Rows with a null doc_id keep their row.
Repeated rows fall together. Texts of any length are taken whole, in pieces of bounded size. Equal distances tie to the smallest fingerprint, which
changes no component. An empty table gives an empty result. Only doc_id and text are read, so other columns may have any names.
"""
from __future__ import annotations

from itertools import islice

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window, functions as F

from .common import discard, lean, text_batches, written
from .components import connected_components

RADIUS, BITS, SHINGLE = 3, 64, 3
PIECE = 1 << 15  # shingles counted at once
EMIT_ROWS = 10_000  # fingerprints a task that emits codes


def _shingles(words: list[bytes], n: int):
    if len(words) <= n:
        return iter([b" ".join(words)] if words else [])
    return map(b" ".join, zip(*(islice(words, k, None) for k in range(n))))


def simhash(text: str, shingle: int = SHINGLE) -> int:
    """The 64-bit fingerprint as a signed integer. bytes.lower and bytes.split act on ASCII alone, as wanted."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    it, ones, n, digest = _shingles(words, shingle), np.zeros(BITS, np.int64), 0, xxhash.xxh64_digest
    while part := [digest(s, 42) for s in islice(it, PIECE)]:
        ones += np.unpackbits(np.frombuffer(b"".join(part), np.uint8)).reshape(-1, BITS).sum(axis=0, dtype=np.int32)
        n += len(part)
    return int.from_bytes(np.packbits(2 * ones > n).tobytes(), "big", signed=True)


def _fingerprint(shingle: int):
    def run(batches):
        for batch in batches:
            col = batch.column(1)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([simhash(col[k].as_py(), shingle) for k in range(batch.num_rows)], pa.int64())], names=["doc_id", "fp"])

    return run


def fingerprints(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """(doc_id, fp) for every row of `docs`."""
    return text_batches(docs, _fingerprint(shingle), "doc_id long, fp long")


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def flip_masks() -> tuple[list[int], list[int]]:
    """Masks of no or one flipped bit, and of two bits at most 21 places apart on the circle of 64."""
    one = [0] + [_signed(1 << i) for i in range(BITS)]
    two = sorted({_signed(1 << i | 1 << (i + k) % BITS) for i in range(BITS) for k in range(1, 22)})
    return one, two


def _half_codes(fp):
    """Codes of both 32-bit halves, tagged by a low bit: the half itself, and if its parity is odd its 1-bit neighbours."""
    flips = F.array(*[F.lit(1 << i).cast("long") for i in range(32)])

    def codes(half, tag: int):
        own = F.when(F.bit_count(half) % 2 == 1, F.concat(F.array(half), F.transform(flips, lambda m: half.bitwiseXOR(m)))).otherwise(F.array(half))
        return F.transform(own, lambda c: F.shiftleft(c, 1).bitwiseOR(F.lit(tag).cast("long")))

    return F.concat(codes(fp.bitwiseAND(F.lit(0xFFFFFFFF).cast("long")), 0), codes(F.shiftrightunsigned(fp, 32), 1))


def close_links(fps: DataFrame) -> DataFrame:
    """Links (a, b) of distinct fingerprints `fp` within 3 bits, enough of them to connect all that are linked.

    Say x and y differ in d <= 3 bits. d = 1: x is a code of itself and a neighbour of y. d = 2: both are one
    bit from a code between them. d = 3: the odd one emits a code two bits off that is one bit from the even one.
    In each case they meet at a code where one is at most 1 away. There every fingerprint that met is linked to
    the smallest that is at most 1 away: at most 2 + 1 bits off, so each link is true, and x and y get connected.
    """
    halves = fps.select("fp", F.explode(_half_codes(F.col("fp"))).alias("code"))
    shared = halves.groupBy("code").agg(F.min("fp").alias("lo"), F.max("fp").alias("hi")).where("lo <> hi").select("code")
    maybe = written(halves.join(shared, "code", "left_semi").select("fp").distinct(), "maybe-close")
    one, two = flip_masks()
    near, far = (F.array(*[F.lit(m).cast("long") for m in ms]) for ms in (one, two))
    maybe = maybe.repartition(1 + maybe.count() // EMIT_ROWS, "fp")  # a fingerprint emits up to 1408 codes: many tasks for a small table
    emitted = maybe.select("fp", F.explode(F.when(F.bit_count("fp") % 2 == 1, F.concat(near, far)).otherwise(near)).alias("mask"))
    met = emitted.select("fp", F.col("fp").bitwiseXOR(F.col("mask")).alias("code"), (F.bit_count("mask") <= 1).alias("hub_ok"))
    hub = F.min(F.when(F.col("hub_ok"), F.col("fp"))).over(Window.partitionBy("code"))
    pairs = met.withColumn("hub", hub).where("hub is not null and hub <> fp").select(F.greatest("fp", "hub").alias("a"), F.least("fp", "hub").alias("b")).distinct()
    return pairs.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= RADIUS)


def simhash_components(docs: DataFrame, shingle: int = SHINGLE) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id for every row of `docs` (doc_id, text).

    component_id is the smallest doc_id reachable over links, the row's own included; null if all of these are null.
    """
    marked = written(fingerprints(docs, shingle), "fingerprints")
    firsts = marked.groupBy("fp").agg(F.min("doc_id").alias("first_doc"))
    roots = connected_components(close_links(firsts.select("fp")), "a", "b")
    rooted = firsts.join(roots, F.col("fp") == F.col("node"), "left").select("fp", "first_doc", F.coalesce("root", "fp").alias("root"))
    groups = rooted.groupBy("root").agg(F.min("first_doc").alias("component_id")).withColumnRenamed("root", "r_")
    of_fp = rooted.join(groups, F.col("root") == F.col("r_")).select(F.col("fp").alias("f_"), "component_id")
    return marked.join(of_fp, F.col("fp") == F.col("f_")).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


# ---- groups of similar texts: ball hashing, then bands of minima of the word shingles for pairs that are similar beyond 3 bits ----

BANDS, SIG = 40, 320  # 8 minima a band
CELL = 256  # texts a side in a block of pairs
STAR_ROUNDS = 2
SIMILARITY, WORDS = 0.8, 5
SKETCH_SCHEMA = "doc_id long, key string, codes array<long>, fp long"
NONE = np.iinfo(np.uint64).max
_RNG = np.random.default_rng(11)
_FACTORS = _RNG.integers(0, 1 << 63, SIG, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ORDER = _RNG.permuted(np.tile(np.arange(SIG, dtype=np.int16), (SIG, 1)), axis=1)  # row b: where the empty bin b looks, in order
_RANK = np.argsort(_ORDER, axis=1).astype(np.int16)


def _filled(least: np.ndarray) -> np.ndarray:
    """The minima, an empty bin taking that of the first filled one in its own fixed order: each bin agrees with about the Jaccard similarity."""
    empty = least == NONE
    fill, todo = np.flatnonzero(~empty), np.flatnonzero(empty)
    if not len(fill) or not len(todo):
        return least
    src = np.arange(SIG)
    if len(fill) <= SIG // 4:
        src[todo] = fill[_RANK[np.ix_(todo, fill)].argmin(axis=1)]
    else:
        step = 0
        while len(todo):
            at = _ORDER[todo, step]
            found = ~empty[at]
            src[todo[found]] = at[found]
            todo, step = todo[~found], step + 1
    return least[src]


def sketch(text: str, words_n: int = WORDS) -> tuple[str, list[int]]:
    """(digest of the words, codes of BANDS bands of the minima of SIG bins of the word shingles)."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    key = xxhash.xxh3_128_hexdigest(b" ".join(words))
    least = np.full(SIG, NONE, np.uint64)
    it = _shingles(words, words_n)
    # bin b holds the hashes from b / SIG on of their range; edges rounded up
    edges = np.array([-(-(b << 64) // SIG) for b in range(SIG)], np.uint64)
    while part := [xxhash.xxh64_digest(s, 7) for s in islice(it, PIECE)]:
        h = np.sort(np.frombuffer(b"".join(part), ">u8").astype(np.uint64))
        at = np.searchsorted(h, edges)
        ends = np.append(at[1:], len(h))
        got = h[np.minimum(at, len(h) - 1)]
        least = np.where(at < ends, np.minimum(least, got), least)
    if (least == NONE).all():
        return key, []
    return key, (_filled(least) * _FACTORS).reshape(BANDS, -1).sum(axis=1).view(np.int64).tolist()


def _sketches(words_n: int):
    def run(batches):
        for batch in batches:
            ids, col = batch.column(0).to_pylist(), batch.column(1)
            for at in range(0, len(ids), 1000):
                got = [sketch(col[k].as_py(), words_n) for k in range(at, min(at + 1000, len(ids)))]
                fps = pa.array([simhash(col[k].as_py()) for k in range(at, at + len(got))], pa.int64())
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, len(got)), pa.array([g[0] for g in got]), pa.array([g[1] for g in got], pa.list_(pa.int64())), fps], names=["doc_id", "key", "codes", "fp"])

    return run


def shingle_set(text: str, words_n: int = WORDS) -> np.ndarray:
    """The sorted distinct 64-bit hashes of the word shingles."""
    words = text.encode("utf-8", "surrogatepass").lower().split()
    return np.unique(np.frombuffer(b"".join([xxhash.xxh64_digest(s, 7) for s in _shingles(words, words_n)]), ">i8").astype(np.int64))


def _shingle_sets(words_n: int):
    def run(batches):
        for batch in batches:
            col = batch.column(1)
            for at in range(0, batch.num_rows, 100):
                part = batch.column(0).slice(at, 100)
                sets = [shingle_set(col[k].as_py(), words_n) for k in range(at, at + len(part))]
                yield pa.RecordBatch.from_arrays([part, pa.array(sets, pa.list_(pa.int64()))], names=["doc_id", "has"])

    return run


def _similar(least: float):
    def run(batches):
        for batch in batches:
            (fa, ea), (fb, eb) = ((c.flatten().to_numpy(), np.concatenate([[0], np.cumsum(c.value_lengths().to_numpy(zero_copy_only=False))])) for c in (batch.column(2), batch.column(3)))
            ok = []
            for k in range(batch.num_rows):
                a, b = fa[ea[k] : ea[k + 1]], fb[eb[k] : eb[k + 1]]
                both = len(np.intersect1d(a, b, assume_unique=True))
                ok.append(both >= least * (len(a) + len(b) - both) - 1e-9)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(ok, pa.bool_()))

    return run


def ball_pairs(one: DataFrame) -> DataFrame:
    """(rep, hub), rep > hub, of `one` (rep, fp): texts of one fingerprint with the first of them, and the firsts of fingerprints linked by ball hashing."""
    firsts = one.groupBy(F.col("fp").alias("f_")).agg(F.min("rep").alias("first_"))
    same = one.join(firsts, F.col("fp") == F.col("f_")).where("rep <> first_").select("rep", F.col("first_").alias("hub"))
    a, b = (firsts.select(F.col("f_").alias(f"f{k}"), F.col("first_").alias(f"i{k}")) for k in (1, 2))
    close = close_links(firsts.select(F.col("f_").alias("fp"))).join(a, F.col("a") == F.col("f1")).join(b, F.col("b") == F.col("f2"))
    return same.unionByName(close.select(F.greatest("i1", "i2").alias("rep"), F.least("i1", "i2").alias("hub")))


def shared_codes(codes: DataFrame) -> DataFrame:
    """(code, rep, n_) of `codes` (rep, code) where n_ > 1 texts have the code."""
    many = codes.groupBy("code").agg(F.count("*").alias("n_")).where("n_ > 1")
    return codes.join(many, "code")


def weighted(shared: DataFrame) -> DataFrame:
    """`shared` with w_, the texts met at all codes of the text: the original of many copies meets more than any copy does."""
    w = shared.groupBy(F.col("rep").alias("wr_")).agg(F.sum(F.col("n_") - 1).alias("w_"))
    return shared.join(w, F.col("rep") == F.col("wr_")).drop("wr_")


def open_members(shared: DataFrame, roots: DataFrame | None) -> DataFrame:
    """`shared` with of_, the component by `roots` (node, root), at codes where components differ."""
    if roots is None:
        return shared.withColumn("of_", F.col("rep"))
    member = shared.join(roots, F.col("rep") == F.col("node"), "left").withColumn("of_", F.coalesce("root", "rep")).drop("node", "root")
    mixed = member.groupBy("code").agg(F.min("of_").alias("lo_"), F.max("of_").alias("hi_")).where("lo_ <> hi_").select("code")
    return member.join(mixed, "code", "left_semi")


def star_pairs(member: DataFrame, tried: DataFrame | None) -> DataFrame:
    """(rep, hub), one a text at most: each with the weightiest text of its codes, if that is in another component and wasn't tried."""
    hub = member.groupBy("code").agg(F.max(F.struct("w_", (-F.col("rep")).alias("minus"), F.col("of_").alias("at_"))).alias("h_"))
    met = member.join(hub, "code").where((F.col("of_") != F.col("h_.at_")) & (F.col("rep") != -F.col("h_.minus"))).select("rep", F.col("h_.w_").alias("w_"), F.col("h_.minus").alias("minus"))
    if tried is not None:
        met = met.join(tried.select(F.col("rep").alias("tr_"), F.col("hub").alias("th_")), (F.col("rep") == F.col("tr_")) & (F.col("minus") == -F.col("th_")), "left_anti")
    best = met.groupBy("rep").agg(F.max(F.struct("w_", "minus")).alias("b_"))
    return best.select("rep", (-F.col("b_.minus")).alias("hub"))


MASKS = [f"m{k}" for k in range(16)]  # 1024 bits


def _masked(batches):
    for batch in batches:
        rows = []
        for k in range(batch.num_rows):
            has = batch.column(1)[k].values.to_numpy()
            own = batch.column(2)[k].values
            common = has if own is None else np.setdiff1d(has, own.to_numpy(), assume_unique=True)
            bits = np.zeros(1024, bool)
            bits[(common.view(np.uint64) >> np.uint64(54)).astype(np.int64)] = True
            rows.append((len(has), len(common), np.packbits(bits).view(np.int64)))
        masks = np.array([r[2] for r in rows], np.int64).reshape(len(rows), len(MASKS))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), *[pa.array(masks[:, k]) for k in range(len(MASKS))]], names=["s_", "size", "common", *MASKS])


def sizes_of(sets: DataFrame, member: DataFrame) -> DataFrame:
    """(s_, size, common, m0 ..) of the texts of `member`: how many shingles, how many of these any other of the texts has, and a bit for each hash range that these fall in."""
    mine = sets.join(member.select(F.col("rep").alias("m_")).distinct(), F.col("doc_id") == F.col("m_"), "left_semi")
    each = mine.select("doc_id", F.explode("has").alias("s"))
    only = each.groupBy("s").agg(F.count("*").alias("n"), F.min("doc_id").alias("doc")).where("n = 1").groupBy("doc").agg(F.collect_list("s").alias("own"))  # a part of one text
    schema = "s_ long, size long, common long, " + ", ".join(f"{m} long" for m in MASKS)
    return mine.join(only, F.col("doc_id") == F.col("doc"), "left").select("doc_id", "has", "own").mapInArrow(lean(_masked), schema)


def other_pairs(member: DataFrame, sizes: DataFrame, least: float) -> DataFrame:
    """Distinct (rep, hub), rep > hub: all pairs of `member` with a code in common and in different components that can be similar.

    Two texts share no more than the common shingles of either, less one for each hash range where it has some and the other has none; with n shared
    the similarity is at most n / (size + size - n). So copies that differ from a lost original in different places part without a
    comparison. A code of many texts is cut into CELL^2 blocks of pairs, so no task gets all of its pairs.
    """
    parts = F.ceil(F.col("n_") / CELL).cast("int")
    member = member.join(sizes, F.col("rep") == F.col("s_")).where(F.col("common") >= least * F.col("size") - 1e-9)
    member = written(member.withColumn("at", F.pmod(F.xxhash64("rep"), parts).cast("int")), "open-members")
    low = member.select("code", "rep", "of_", "size", "common", *MASKS, F.col("at").alias("i"), F.explode(F.sequence("at", parts - 1)).alias("j"))
    other = [F.col(m).alias(f"o{m}") for m in MASKS]
    high = member.select(F.col("code").alias("c_"), F.col("rep").alias("hub"), F.col("of_").alias("with_"), F.col("size").alias("z_"), F.col("common").alias("k_"), *other, F.col("at").alias("j_"), F.explode(F.sequence(F.lit(0), "at")).alias("i_"))

    def only(mine: str, theirs: str):
        out = F.lit(0)
        for m in MASKS:
            out = out + F.bit_count(F.col(f"{mine}{m}").bitwiseAND(F.bitwise_not(F.col(f"{theirs}{m}"))))
        return out

    same = F.least(F.col("common") - only("", "o"), F.col("k_") - only("o", ""))
    can = same >= least * (F.col("size") + F.col("z_") - same) - 1e-9
    met = low.join(high, (F.col("code") == F.col("c_")) & (F.col("i") == F.col("i_")) & (F.col("j") == F.col("j_")) & (F.col("of_") != F.col("with_")) & ((F.col("i") < F.col("j")) | (F.col("rep") < F.col("hub"))) & can)
    return met.select(F.greatest("rep", "hub").alias("rep"), F.least("rep", "hub").alias("hub")).distinct()


def joined_components(roots: DataFrame, found: DataFrame) -> DataFrame:
    """(node, root) over the links (a, b) of `found` and all that `roots` was made of: its rows connect the same texts."""
    return connected_components(found.unionByName(roots.select(F.col("node").alias("a"), F.col("root").alias("b"))), "a", "b")


def similar_groups(docs: DataFrame, similarity: float = SIMILARITY, words_n: int = WORDS) -> DataFrame:
    """(doc_id, component_id) of every row: components over pairs whose `words_n`-word shingles have the similarity.

    First ball hashing: texts of equal fingerprints and those that `close_links` links, as in `simhash_components`. Texts at 0.8 differ
    in about 10 bits, beyond any ball that can be emitted, so further candidates agree on one of 40 bands of 8 minima of
    the shingles. A minimum agrees with the Jaccard
    similarity J, whatever the edit, so a pair is missed with about (1 - J^8)^40: 6e-4 at 0.8, less above. Of these each
    text is compared with the weightiest one of its codes, which joins the copies of an original in linear work, then
    all pairs of a code that this left unconnected and that may still be similar. Every pair is verified by the exact
    Jaccard similarity of the sets of hashed shingles. Texts of equal words are one, and rows of one doc_id are one document.

    Null and empty texts have no shingles and are alike by their equal (empty) words. Rows with a null doc_id have a component
    only by their words; it is null if no row of these has a doc_id. An empty table gives an empty result.
    """
    made = written(text_batches(docs, lean(_sketches(words_n)), SKETCH_SCHEMA), "sketches")
    one = written(made.groupBy("key").agg(F.min("doc_id").alias("rep"), F.first("codes").alias("codes"), F.first("fp").alias("fp")).where("rep is not null"), "distinct-sketches")
    rows, reps = written(made.select("doc_id", "key"), "keys"), written(one.select("key", "rep"), "reps")
    discard(made)
    close = written(ball_pairs(one.select("rep", "fp")), "ball-pairs")
    shared = written(weighted(shared_codes(one.select("rep", F.explode(F.array_distinct("codes")).alias("code")))), "shared-codes")
    discard(one)
    ids = shared.select("rep").unionByName(close.select("rep")).unionByName(close.select(F.col("hub").alias("rep"))).select(F.col("rep").alias("asked_")).distinct()
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    texts = texts.join(ids, F.col("doc_id") == F.col("asked_"), "left_semi")
    sets = written(text_batches(texts, lean(_shingle_sets(words_n)), "doc_id long, has array<long>").dropDuplicates(), "shingle-sets")
    held = [shared, sets, close]

    def verified(pairs):
        a, b = (sets.select(F.col("doc_id").alias(f"r{k}"), F.col("has").alias(f"s{k}")) for k in (1, 2))
        both = pairs.join(a, F.col("rep") == F.col("r1")).join(b, F.col("hub") == F.col("r2"))
        found = written(both.select("rep", "hub", "s1", "s2").mapInArrow(lean(_similar(similarity)), "a long, b long"), "similar-pairs")
        held.append(found)
        return found

    tried = close
    roots = connected_components(verified(close), "a", "b")
    for _ in range(STAR_ROUNDS):
        member = open_members(shared, roots)
        pairs = written(star_pairs(member, tried), "star-pairs")
        held.append(pairs)
        tried = tried.unionByName(pairs)
        held.append(roots)
        roots = joined_components(roots, verified(pairs))
    member = written(open_members(shared, roots), "mixed-codes")
    rest = other_pairs(member, sizes_of(sets, member), similarity)
    both_ways = tried.unionByName(tried.select(F.col("hub").alias("rep"), F.col("rep").alias("hub")))
    found = verified(rest.join(both_ways, ["rep", "hub"], "left_anti"))
    held += [member, roots]
    roots = joined_components(roots, found)
    of_rep = reps.join(roots, F.col("rep") == F.col("node"), "left").select(F.col("key").alias("k_"), F.coalesce("root", "rep").alias("component_id"))
    out = written(rows.join(of_rep, F.col("key") == F.col("k_"), "left").select("doc_id", "component_id"), "groups")
    discard(*held, roots, rows, reps)
    return out


MOST_DROPPED = 2_000_000  # doc_ids (16 bytes and their places in a table) that are broadcast; more are joined, which shuffles whole rows


def keep_one_of_each(docs: DataFrame, similarity: float = SIMILARITY, words_n: int = WORDS) -> DataFrame:
    """`docs`, all columns, with the row of the smallest doc_id of each group; rows with a null doc_id stay."""
    groups = similar_groups(docs, similarity, words_n)
    out = groups.where("doc_id is not null and doc_id <> component_id").select(F.col("doc_id").alias("dropped_")).distinct()
    out = F.broadcast(out) if out.limit(MOST_DROPPED + 1).count() <= MOST_DROPPED else out
    kept = docs.withColumnRenamed("dropped_", "dropped__") if "dropped_" in docs.columns else docs
    kept = kept.join(out, kept["doc_id"].cast("long") == out["dropped_"], "left_anti")
    return kept.withColumnRenamed("dropped__", "dropped_") if "dropped_" in docs.columns else kept
