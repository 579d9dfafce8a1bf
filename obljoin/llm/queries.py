"""The driver queries of the training-data operators, and their DuckDB SQL where it can express them."""

from __future__ import annotations

from collections.abc import Callable

import corpus_pipeline
import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from obljoin.llm import ann, chat, langid, mixing, toxicity
from obljoin.llm.bpe import token_digests
from obljoin.llm.chaining import repeated_passages
from obljoin.llm.common import saved, table
from obljoin.llm.exact_dedup import exact_dedup
from obljoin.llm.simhash import as_hex, simhash_groups
from obljoin.llm.suffix_dedup import strip

RANKS = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")


def op1_adaptive_ann(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = langid.train(docs, langid.remainder("doc_id", 3) != 1)
    return langid.identify(docs, model).select(
        "doc_id", (langid.remainder("doc_id", 3) == 1).alias("held_out"), "lang_pred", "score", "ambiguous"
    )


def op3_collinear_chaining(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_passages(table(spark, sf_dir, "documents"))


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return saved(token_digests(table(spark, sf_dir, "documents"), RANKS))


def op5_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    given = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-7, 0, "user", probe), (-7, 1, "assistant", probe)], "conv_id long, turn long, role string, text string")
    return chat.read_back(chat.conversations(chat.from_turns(given.unionByName(extra))))


def op6_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup(table(spark, sf_dir, "documents")).select("doc_id", "keep_id", "group_size", "kept", "text_sha256")


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_groups(table(spark, sf_dir, "documents")).select("doc_id", as_hex(F.col("fp")).alias("fingerprint"), "component_id")


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    levels, weights = mixing.document_tree()
    mixed = mixing.mix(table(spark, sf_dir, "documents"), levels, weights, budget=0.6, max_epochs=2, seed=8)
    return mixed.select("doc_id", mixing.source_domain().alias("domain"), "lang", "source", "n_tokens", "copies")


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = toxicity.train(docs, table(spark, sf_dir, "labels"), langid.remainder("doc_id", 5) != 0)
    scored = toxicity.score(docs, model)
    return scored.select(
        "doc_id", (langid.remainder("doc_id", 5) == 0).alias("held_out"), "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted")
    )


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return strip(table(spark, sf_dir, "documents"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_adaptive_ann": op1_adaptive_ann,
    "op2_language_id": op2_language_id,
    "op3_collinear_chaining": op3_collinear_chaining,
    "op4_byte_bpe": op4_byte_bpe,
    "op5_chat_format": op5_chat_format,
    "op6_exact_dedup": op6_exact_dedup,
    "op7_simhash": op7_simhash,
    "op8_mixing": op8_mixing,
    "op9_toxicity": op9_toxicity,
    "op10_suffix_dedup": op10_suffix_dedup,
    "pipeline": pipeline,
}

def _shares(level: int, family: str) -> str:
    """One level of the tree in SQL: children by rising capacity per weight; those whose share exceeds it are full, the others split the rest."""
    over = f"PARTITION BY {family} " if family else ""
    keys = ", ".join(("domain", "lang", "source")[:level])
    budget = f"(SELECT b FROM g{level - 1} AS up WHERE {' AND '.join(f'up.{k} = f{level}.{k}' for k in family.split(', '))})" if family else "(SELECT b FROM g0)"
    return f"""
        p{level} AS (SELECT *, {budget} AS b,
                            coalesce(sum(cap) OVER ({over}ORDER BY cap / w, {keys} ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS spent,
                            sum(w) OVER ({over}ORDER BY cap / w, {keys} ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS open_w FROM f{level}),
        s{level} AS (SELECT *, cap * open_w <= (b - spent) * w AS is_full FROM p{level}),
        g{level} AS (SELECT {keys}, CASE WHEN is_full THEN cap ELSE (b - sum(CASE WHEN is_full THEN cap ELSE 0 END) OVER ({over})) * w
                            / sum(CASE WHEN is_full THEN 0 ELSE w END) OVER ({over}) END AS b FROM s{level})"""


def mixing_sql() -> str:
    domains = " ".join(f"WHEN '{d[0]}' THEN {w}" for d, w in mixing.DOMAIN_WEIGHTS.items())
    languages = " ".join(f"WHEN '{k}' THEN {w}" for k, w in mixing.LANGUAGE_WEIGHTS.items())
    return f"""
        WITH d AS (SELECT doc_id, 'domain' || (CAST(regexp_extract(source, '([0-9]+)$', 1) AS INTEGER) % 4) AS domain, lang, source,
                          len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+')) AS n FROM documents),
        f3 AS (SELECT domain, lang, source, CAST(sum(n) AS DOUBLE) AS n, CAST(sum(n) * 2 AS DOUBLE) AS cap, CAST(1 AS DOUBLE) AS w FROM d GROUP BY ALL HAVING sum(n) > 0),
        f2 AS (SELECT domain, lang, sum(cap) AS cap, CAST(CASE lang {languages} ELSE 1 END AS DOUBLE) AS w FROM f3 GROUP BY domain, lang),
        f1 AS (SELECT domain, sum(cap) AS cap, CAST(CASE domain {domains} ELSE 1 END AS DOUBLE) AS w FROM f2 GROUP BY domain),
        g0 AS (SELECT least(floor(sum(n) * 6 / 10), sum(cap)) AS b FROM f3), {_shares(1, "")}, {_shares(2, "domain")}, {_shares(3, "domain, lang")},
        k AS (SELECT domain, lang, source, CAST(floor(g3.b + 1e-6) AS BIGINT) AS given, CAST(f3.n AS BIGINT) AS held FROM g3 JOIN f3 USING (domain, lang, source)),
        r AS (SELECT d.*, given // held AS whole, given % held AS rest FROM d JOIN k USING (domain, lang, source)),
        o AS (SELECT *, sum(n) OVER (PARTITION BY domain, lang, source ORDER BY md5('8:' || whole || ':' || doc_id)[1:15], doc_id, n ROWS UNBOUNDED PRECEDING) AS upto FROM r),
        c AS (SELECT *, whole + CASE WHEN rest > 0 AND 2 * upto - n <= 2 * rest THEN 1 ELSE 0 END AS copies FROM o)
        SELECT doc_id, domain, lang, source, CAST(n AS BIGINT) AS n_tokens, CAST(copies AS BIGINT) AS copies FROM c WHERE copies > 0
    """


ORACLES: dict[str, str] = {
    "op8_mixing": mixing_sql(),
    "op5_chat_format": r"""
        WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
                   UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
             m AS (SELECT *, len(regexp_extract_all(text, '\\|<s>|</s>|\[INST\]|\[/INST\]|<<SYS>>|<</SYS>>|\[ROLE\]|\[/ROLE\]')) + length(text)
                          + CASE role WHEN 'user' THEN 16 WHEN 'system' THEN 15 WHEN 'assistant' THEN 4
                            ELSE 17 + length(role) + len(regexp_extract_all(role, '\\|<s>|</s>|\[INST\]|\[/INST\]|<<SYS>>|<</SYS>>|\[ROLE\]|\[/ROLE\]')) END AS chars FROM c)
        SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
               CAST(sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS BIGINT) AS loss_chars,
               sha256(string_agg(CASE WHEN role = 'assistant' THEN text ELSE '' END, '' ORDER BY turn, role, text)) AS loss_sha256,
               CAST(sum(chars) AS BIGINT) AS formatted_chars
        FROM m GROUP BY conv_id
    """,
    "op6_exact_dedup": """
        WITH t AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS body FROM documents),
             g AS (SELECT body, max(doc_id) AS keep_id, count(*) AS group_size, sha256(body) AS text_sha256 FROM t GROUP BY body)
        SELECT t.doc_id, g.keep_id, g.group_size, t.doc_id = g.keep_id AS kept, g.text_sha256 FROM t JOIN g ON t.body = g.body
    """,
}
