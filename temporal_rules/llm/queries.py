"""The corpus operators' queries over the given tables; each derives its digest columns from its operator."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op1_stable_projection_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .stable_ann import nearest_neighbours

    return nearest_neighbours(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0, k=10)


def op2_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .token_store import write_store

    store = write_store(table(spark, sf_dir, "documents"), vocabulary(), end_id=0)
    return store.documents(spark)


def op3_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .minhash_dedup import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op4_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .html_blocks import extract

    return extract(table(spark, sf_dir, "pages"))


def op5_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mixing import mix, taken_words

    return taken_words(mix(table(spark, sf_dir, "documents"))).select("doc_id", "size", "source_size", "target", "taken")


def op6_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .toxicity import fit, held_out, score_documents

    docs = table(spark, sf_dir, "documents")
    scored = score_documents(docs, fit(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out().alias("held_out"), "score", "predicted", "evidence")


def op7_quote_threads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reply-ordered conversations without quotes."""
    from .chat_threads import conversations

    return conversations(table(spark, sf_dir, "conversations"))


def op8_shard_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's slot and shard, and its words, so that shards' sizes can be summed."""
    from .common import words_of
    from .shard_table import place

    docs = table(spark, sf_dir, "documents").select("doc_id", words_of().alias("words"))
    return place(docs, [f"shard-{i:03d}" for i in range(256)], ["doc_id"])


def op9_vector_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .ego_join import similar_vectors

    return similar_vectors(table(spark, sf_dir, "embeddings"), t=0.95)


def op10_pattern_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .packing import pack_documents

    out = pack_documents(table(spark, sf_dir, "documents"), vocabulary(), end_id=2, size=1024)
    return out.select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


QUERIES = {
    "op1_stable_projection_ann": op1_stable_projection_ann,
    "op2_token_files": op2_token_files,
    "op3_near_duplicates": op3_near_duplicates,
    "op4_main_text": op4_main_text,
    "op5_source_mix": op5_source_mix,
    "op6_toxicity": op6_toxicity,
    "op7_quote_threads": op7_quote_threads,
    "op8_shard_table": op8_shard_table,
    "op9_vector_near_duplicates": op9_vector_near_duplicates,
    "op10_pattern_packing": op10_pattern_packing,
}

_REACH = """r(x, y) as (select i, i from v union select r.x, l.b from r join l on r.y = l.a),
 c as (select x, min(y) y from r group by x)"""

#: All pairs that share a shingle, and all pairs of vectors; components by reachability.
ORACLE_SQL: dict[str, str] = {
    "op3_near_duplicates": rf"""with recursive w as (select doc_id i, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') ws from documents),
 v as (select i from w),
 s as (select distinct i, unnest(case when len(ws) = 0 then []::varchar[] when len(ws) < 5 then [array_to_string(ws, ' ')] else list_transform(range(1, len(ws) - 3), lambda k: array_to_string(ws[k:k + 4], ' ')) end) sh from w),
 n as (select i, count(*) n from s group by i),
 p as (select a.i a, b.i b, count(*) c from s a join s b on a.sh = b.sh and a.i <> b.i group by 1, 2),
 l as (select a, b from p join n x on x.i = a join n y on y.i = b where 100 * c >= 75 * (x.n + y.n - c)),
 {_REACH}
 select w.i doc_id, coalesce(n.n, 0)::bigint n_shingles, c.y component_id, w.i = c.y kept from w join c on c.x = w.i left join n on n.i = w.i""",
    "op9_vector_near_duplicates": f"""with recursive e as (select vec_id i, embedding::double[] x from embeddings where embedding is not null and list_bool_and(list_transform(embedding, lambda q: q is not null and isfinite(q))) and list_bool_or(list_transform(embedding, lambda q: q <> 0))),
 v as (select vec_id i from embeddings),
 l as (select a.i a, b.i b from e a join e b on a.i <> b.i and list_cosine_similarity(a.x, b.x) >= 0.95),
 {_REACH}
 select c.x vec_id, (select count(*) from l where l.a = c.x)::bigint n_links, c.y component_id, c.x = c.y kept from c""",
}
