"""The ten queries opN_<name>, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wordlid.io import read_table
from wordlid.llm import bpe, chat, exactdedup, fingerprint, langid, minhash, mixing, quality, sharding, tokencounts

TOKENIZER = "word_bpe_49k.json"


def tokenizer_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def remainder(of: int):
    """crc32 of doc_id as text, modulo `of`."""
    return F.crc32(F.col("doc_id").cast("string")) % of


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = sharding.shard_documents(read_table(spark, sf_dir, "documents"), 40)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op2_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exactdedup.exact_duplicates(read_table(spark, sf_dir, "documents"))


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokencounts.token_histogram(read_table(spark, sf_dir, "documents"), tokenizer_path())


def op4_chat_collapse(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.collapse(read_table(spark, sf_dir, "conversations"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    model = langid.train(docs, learn=~remainder(4).eqNullSafe(F.lit(2)))
    return langid.classify(docs, model).select("doc_id", remainder(4).eqNullSafe(F.lit(2)).alias("held_out"), "lang_pred", "score", "accepted")


def op6_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.fingerprints(read_table(spark, sf_dir, "documents"))


def op7_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digests(read_table(spark, sf_dir, "documents"), tokenizer_path())


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(read_table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "source", "first_shard", "last_shard")


def op9_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(read_table(spark, sf_dir, "documents"), 85)


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = read_table(spark, sf_dir, "documents"), read_table(spark, sf_dir, "labels")
    model = quality.train(docs, labels, learn=remainder(5) != 0)
    held = remainder(5).eqNullSafe(F.lit(0))
    return quality.classify(docs, model).select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_sharding, op2_exact_dedup, op3_token_counts, op4_chat_collapse, op5_language_id, op6_fingerprints, op7_bpe, op8_mixing, op9_near_dedup, op10_quality)
}

NORMALISED = r"regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g')"

ORACLE: dict[str, str] = {
    "op2_exact_dedup": f"""
        WITH n AS (SELECT doc_id, {NORMALISED} AS norm FROM documents),
             g AS (SELECT norm, min(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY norm)
        SELECT doc_id, keep_id, group_size, doc_id = keep_id AS kept, sha256(norm) AS text_sha256
        FROM n JOIN g USING (norm)""",
    "op4_chat_collapse": """
        WITH t AS (SELECT conv_id, coalesce(turn, -1) AS turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations),
             s AS (SELECT conv_id, count(*) AS n_turns, list(role || chr(0) || text ORDER BY turn, role) AS turns,
                          string_agg('<|' || role || '|>' || chr(10) || text || chr(10), '' ORDER BY turn, role) AS rendered FROM t GROUP BY conv_id),
             d AS (SELECT turns, n_turns, rendered, min(conv_id) AS conv_id, count(*) AS copies FROM s GROUP BY turns, n_turns, rendered)
        SELECT conv_id, n_turns, copies, rendered FROM d
        WHERE NOT EXISTS (SELECT 1 FROM d AS o WHERE o.turns[1] = d.turns[1] AND o.n_turns > d.n_turns AND list_slice(o.turns, 1, d.n_turns) = d.turns)""",
    "op9_near_dedup": r"""
        WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
             sh AS (SELECT doc_id, CASE WHEN len(ws) >= 5 THEN list_distinct(list_transform(generate_series(1, len(ws) - 4), lambda i: array_to_string(ws[i:i + 4], ' ')))
                                        WHEN len(ws) > 0 THEN [array_to_string(ws, ' ')] ELSE [] END AS s FROM w),
             n AS (SELECT doc_id, len(s) AS n FROM sh),
             e AS (SELECT doc_id, unnest(s) AS x FROM sh),
             p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM e a JOIN e b ON a.x = b.x AND a.doc_id <> b.doc_id GROUP BY 1, 2),
             l AS (SELECT p.a, p.b FROM p JOIN n x ON x.doc_id = p.a JOIN n y ON y.doc_id = p.b WHERE 100 * i >= 85 * (x.n + y.n - i)),
             r AS (SELECT doc_id AS a, doc_id AS root FROM n UNION SELECT l.b, r.root FROM r JOIN l ON l.a = r.a),
             c AS (SELECT a AS doc_id, min(root) AS component_id FROM r GROUP BY a)
        SELECT n.doc_id, n.n AS n_shingles, c.component_id, n.doc_id = c.component_id AS kept FROM n JOIN c USING (doc_id)""",
}
