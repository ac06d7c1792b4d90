"""The registered queries of the corpus operators, with production parameters, over whole tables."""
from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from .common import discard, labelled_documents, table
from .decontaminate import contaminated_spans
from .language_id import fit_dictionaries, identify_language
from .mixing import mix_positions
from .pii import replace_personal_data
from .quality import PER_CLASS as QUALITY_ROWS, fit_quality, score_quality
from .secrets import find_secrets
from .simhash import simhash_components
from .token_files import document_digests, write_token_file
from .topk import top_k
from .toxicity import PER_CLASS as TOXIC_ROWS, fit_toxicity, score_toxicity

KEY_SETTING, TEST_KEY = "spark.metricspark.surrogateKey", "surrogates-v1"  # the secret key is a setting of the session; tests and checks have none


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op1_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return top_k(vectors, vectors.where(F.col("vec_id") % 50 == 0))


def toxicity_model(spark: SparkSession, sf_dir: str):
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    sample = labelled_documents(docs, labels, "toxic", 5, 0, TOXIC_ROWS)
    model = fit_toxicity(sample)
    discard(sample)
    return model


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_toxicity(table(spark, sf_dir, "documents").select("doc_id", "text"), toxicity_model(spark, sf_dir))


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    sample = labelled_documents(docs, labels, "quality", 5, 0, QUALITY_ROWS)
    forest = fit_quality(sample)
    discard(sample)
    return score_quality(docs.select("doc_id", "text"), forest)


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_positions(table(spark, sf_dir, "documents").select("doc_id", "source"))


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_components(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return replace_personal_data(table(spark, sf_dir, "documents").select("doc_id", "text"), spark.conf.get(KEY_SETTING, TEST_KEY))


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return identify_language(docs, fit_dictionaries(docs))


def op8_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_secrets(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated_spans(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))


def op10_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return document_digests(write_token_file(docs, tokenizer_path()))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_topk, op2_toxicity, op3_quality, op4_mixing, op5_simhash, op6_pii, op7_language, op8_secrets, op9_decontamination, op10_tokens, pipeline)}

ORACLES = {
    "op1_topk": """
        with v as (
            select vec_id, list_transform(embedding, lambda x: floor(256 * x::double)::double) as c
            from embeddings
            where vec_id is not null and embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0
        ), s as (
            select q.vec_id as query_id, d.vec_id, list_inner_product(q.c, d.c)::bigint as score
            from v q join v d on q.vec_id <> d.vec_id where q.vec_id % 50 = 0
        ), r as (
            select query_id, (row_number() over (partition by query_id order by score desc, vec_id))::integer as rank, vec_id, score from s
        )
        select query_id, rank, vec_id, score from r where rank <= 5
    """,
    "op4_mixing": """
        with recursive counted as (
            select source, count(*) as n from documents group by source
        ), weighted as (
            select source, greatest(1, floor(100 * sqrt(n / (select max(n) from counted)) + 0.5))::bigint as u, row_number() over (order by source nulls first) as s from counted
        ), whole as (
            select sum(u)::bigint as w, list(u order by s) as us from weighted
        ), plan as (
            select 0::bigint as t, list_transform(us, lambda x: 0::bigint) as given, 0::bigint as s, 0::bigint as i from whole
            union all
            select t + 1, list_transform(range(1, len(given) + 1), lambda k: case when k = pick then given[k] + 1 else given[k] end), pick, given[pick]
            from (
                select t, given, list_min(list_transform(range(1, len(given) + 1), lambda k:
                    case when given[k] < us[k] and given[k] * w // us[k] <= t then {'due': ((given[k] + 1) * w + us[k] - 1) // us[k], 'k': k} else {'due': 9223372036854775807, 'k': k} end)).k as pick
                from plan, whole where t < w
            )
        ), ranked as (
            select doc_id, source, row_number() over (partition by source order by md5('mix:' || coalesce(doc_id::varchar, '')), doc_id) - 1 as r from documents
        ), blocks as (
            select doc_id, ranked.source, r // 64 as block, r % 64 as place, u, s from ranked join weighted on ranked.source is not distinct from weighted.source
        )
        select doc_id, source, block, (block // u) * w + plan.t - 1 as slot, block * w // u as release, ((block + 1) * w + u - 1) // u as deadline, place
        from blocks join whole on true join plan on plan.s = blocks.s and plan.i = block % u and plan.t > 0
    """,
}
