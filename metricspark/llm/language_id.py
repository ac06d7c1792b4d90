"""Language identification by compression.

Each language has a raw-content zstandard dictionary made of sampled training text. A text is cut into blocks, all
of it, and each block is compressed with every language's dictionary; the language with the fewest bytes in all
wins. The score is the relative margin to the runner-up, scaled to 0..1; a narrow margin marks the row as rejected.

The slices come from hash-chosen places of hash-chosen documents, so that openings that many documents share teach no more
than any other place. With very many languages the dictionaries get smaller together, so that all of them stay under TOTAL_BYTES.

Texts that are null or have no letter are `und` with score 0. Ties go to the alphabetically first language. Texts of any length are
compressed whole, block by block. Repeated rows keep their rows and get equal results; a null doc_id is in no fold. An empty
table gives an empty result, and with no training text at all every row is `und`. Only doc_id, text and, in training,
lang are read, so other columns may have any names.
"""
from __future__ import annotations

import json
import re
import zlib

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, Window, functions as F

from .common import fold, text_batches

DICT_BYTES = 48_000  # per language
TOTAL_BYTES = 24_000_000  # of all dictionaries: what the driver collects and tasks hold
LEAST_BYTES = 1000  # a dictionary under this tells nothing
SAMPLE_DOCS = 200  # documents per language; with DICT_BYTES the bound of what training collects
BLOCK_CHARS = 4_000
PARAMETERS = dict(strategy=zstandard.STRATEGY_BTOPT, min_match=3, search_log=4, chain_log=16, hash_log=16, window_log=18)  # short matches tell languages apart
REJECT_MARGIN = 0.02


def fit_dictionaries(docs: DataFrame, folds: int = 4, out_fold: int = 2, sample_docs: int = SAMPLE_DOCS, dict_bytes: int = DICT_BYTES) -> dict[str, bytes]:
    """Per language, slices of the `sample_docs` documents of smallest hash outside fold `out_fold`, `dict_bytes` in all.

    A first count tells which share of a language's hashes holds that many, so that only a few more than needed are ranked.
    """
    known = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (fold(F.col("doc_id"), folds) != out_fold))
    known = known.select(F.col("lang").cast("string").alias("lang"), F.xxhash64("doc_id").alias("h"), F.col("text").cast("string").alias("text"))
    counts = docs.where(F.col("lang").isNotNull() & (fold(F.col("doc_id"), folds) != out_fold)).groupBy(F.col("lang").cast("string").alias("lang")).agg(F.approx_count_distinct("doc_id").alias("n"))
    counts = {r.lang: max(1, r.n) for r in counts.limit(TOTAL_BYTES // LEAST_BYTES + 1).collect()}  # one row a language
    if not counts:
        return {}
    if len(counts) > TOTAL_BYTES // LEAST_BYTES:
        raise ValueError(f"more than {TOTAL_BYTES // LEAST_BYTES} languages")
    dict_bytes = min(dict_bytes, TOTAL_BYTES // len(counts))
    slice_chars = 4 * max(1, dict_bytes // sample_docs)  # what stays after signs and digits are gone is cut to size below
    places = 1 << 30
    share = 1.3 * (sample_docs + 6 * sample_docs**0.5 + 10) * places  # the count is off by up to a few times 5 %
    table = spark_rows(docs.sparkSession, [{"l_": k, "most_": min(places, int(share / n) + 1)} for k, n in counts.items()], "array<struct<l_:string,most_:bigint>>")
    near = known.join(F.broadcast(table), F.col("lang") == F.col("l_")).where(F.pmod(F.col("h"), F.lit(places)) < F.col("most_"))  # a row a language
    start = F.pmod(F.xxhash64("h", F.lit(1)), F.greatest(F.length("text") - slice_chars, F.lit(1))) + 1
    part = F.substring(F.col("text"), start.cast("int"), F.lit(slice_chars))
    near = near.groupBy("lang", "h").agg(F.min(part).alias("part"))
    ranked = near.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.pmod(F.col("h"), F.lit(places)), "h"))).where(F.col("r") <= sample_docs)
    langs: dict[str, list[bytes]] = {}
    for row in ranked.orderBy("lang", "r").select("lang", "part").collect():  # slices of TOTAL_BYTES characters or so
        langs.setdefault(row.lang, []).append(plain(row.part).encode("utf-8", "surrogatepass"))
    return {k: b"".join(x[: max(1, dict_bytes // len(v))] for x in v) for k, v in sorted(langs.items())}


def spark_rows(spark, rows: list[dict], kind: str) -> DataFrame:
    return spark.range(1).select(F.explode(F.from_json(F.lit(json.dumps(rows)), kind)).alias("x")).select("x.*")


words_of = re.compile(r"[^\W\d_]+").findall
_compressors: dict = {}


def _ready(dicts: dict[str, bytes]):
    key = hash(tuple(dicts.items()))
    if key not in _compressors:
        _compressors.clear()
        made = []
        for name, data in dicts.items():
            d = zstandard.ZstdCompressionDict(data, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            p = zstandard.ZstdCompressionParameters(write_content_size=False, write_checksum=False, write_dict_id=False, **PARAMETERS)
            d.precompute_compress(compression_params=p)
            made.append((name, zstandard.ZstdCompressor(compression_params=p, dict_data=d)))
        _compressors[key] = made
    return _compressors[key]


def plain(text: str) -> str:
    """Lower-case words with single spaces: case, punctuation and layout say nothing of a language."""
    return " " + " ".join(words_of(text.lower())) + " "


def classify(text: str, compressors, block_chars: int = BLOCK_CHARS) -> tuple[str, float]:
    if not compressors or not any(map(str.isalpha, text)):
        return "und", 0.0
    text = plain(text)
    blocks = [text[i : i + block_chars].encode("utf-8", "surrogatepass") for i in range(0, len(text), block_chars)]
    sizes = sorted((sum(len(c.compress(b)) for b in blocks), name) for name, c in compressors)
    best = sizes[0]
    margin = 1.0 if len(sizes) == 1 else (sizes[1][0] - best[0]) / max(1, sizes[1][0])
    return best[1], margin


def _predict(dicts: dict[str, bytes], folds: int, out_fold: int, reject_margin: float):
    def run(batches):
        compressors = _ready(dicts)
        for batch in batches:
            ids = batch.column(0).to_pylist()
            got = [classify(batch.column(1)[i].as_py(), compressors) for i in range(batch.num_rows)]
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(0),
                    pa.array([i is not None and zlib.crc32(str(i).encode()) % folds == out_fold for i in ids], pa.bool_()),
                    pa.array([g[0] for g in got], pa.string()),
                    pa.array([min(1.0, g[1] / (g[1] + reject_margin)) if g[1] else 0.0 for g in got], pa.float64()),
                    pa.array([g[1] < reject_margin for g in got], pa.bool_()),
                ],
                names=["doc_id", "held_out", "lang_pred", "score", "rejected"],
            )

    return run


def identify_language(docs: DataFrame, dicts: dict[str, bytes], folds: int = 4, out_fold: int = 2, reject_margin: float = REJECT_MARGIN) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected for every row of `docs` (doc_id, text)."""
    return text_batches(docs, _predict(dicts, folds, out_fold, reject_margin), "doc_id long, held_out boolean, lang_pred string, score double, rejected boolean")
