"""The thin queries opN_<name> and their DuckDB oracles."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import chat, licenses, mixing, near_duplicates, neighbours, piece_bpe, quality, suffix_dedup, token_files, warc
from .common import table, tokenizer_path, workspace


def op1_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Encode every whole text by merge rounds, decode the ids, and digest both."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    path = tokenizer_path("piece_bpe_32k.model")
    ids = piece_bpe.encoded(docs, path, keep_text=False)
    return piece_bpe.decoded(ids, path).select(
        "doc_id",
        F.size("ids").cast("bigint").alias("n_tokens"),
        F.sha2(F.concat_ws(",", F.col("ids").cast("array<string>")), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )


def op2_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Write the ids of all documents to flat files and read place, size and checksum of each document back."""
    docs = table(spark, sf_dir, "documents")
    data = token_files.write(docs, workspace(spark, "token-files"), tokenizer_path("word_bpe_49k.json"))
    return token_files.read(spark, data, checksum_only=True)


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mix all documents to the production weights and count what is taken of each."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return mixing.taken(docs).select("doc_id", "size", "source_size", "target", "taken", "source")


def op4_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scan every whole text for phrases and notices and sum the spans up per document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = licenses.scanned(docs, keep_text=False)
    base = F.filter("spans", lambda s: s["base"])
    starts = F.transform(base, lambda s: s["first_word"])

    def labels(spans):
        return F.array_join(F.array_sort(F.array_distinct(F.transform(spans, lambda s: s["label"]))), ",")

    return out.select(
        "doc_id",
        "n_words",
        F.size(base).cast("bigint").alias("n_base"),
        F.array_min(starts).alias("first_word"),
        F.array_max(starts).alias("last_word"),
        labels(base).alias("base_labels"),
        labels(F.col("spans")).alias("labels"),
        F.coalesce(F.array_max(F.transform("spans", lambda s: s["similarity"])), F.lit(0.0)).alias("score"),
    )


def op5_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 nearest of every row whose id is divisible by 20, among all other rows."""
    return neighbours.nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0, k=20)


def op6_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document: its near-duplicate class and the number of documents that it links to."""
    return near_duplicates.joined(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op7_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Write all pages as archives and describe every record that is read back."""
    path = workspace(spark, "warc")
    pages = table(spark, sf_dir, "pages")
    names = warc.write(warc.deduplicated(pages), path, warc.sample_of(pages))
    return warc.read(spark, path, names, payloads=False).drop("url")


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Remove the bytes of all strings of 200 bytes that begin at two places or more, and digest what stays."""
    return suffix_dedup.digests(table(spark, sf_dir, "documents"))


def op9_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Collapse snapshots of all conversations and render those that stay."""
    return chat.formatted(table(spark, sf_dir, "conversations")).select("conv_id", "n_turns", "n_copies", "rendered")


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per document: the base measures, base_failed and the method's verdict."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return quality.judged(docs).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


def queries() -> dict:
    return {
        "op1_sentencepiece": op1_sentencepiece,
        "op2_token_files": op2_token_files,
        "op3_mixing": op3_mixing,
        "op4_licenses": op4_licenses,
        "op5_neighbours": op5_neighbours,
        "op6_near_duplicates": op6_near_duplicates,
        "op7_warc": op7_warc,
        "op8_suffix_dedup": op8_suffix_dedup,
        "op9_chat": op9_chat,
        "op10_quality_rules": op10_quality_rules,
    }


def oracle_sql() -> dict[str, str]:
    return ORACLES


ORACLES = {
    "op9_chat": """
        WITH t AS (SELECT conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS place,
                          '<|' || coalesce(role, '') || '|>' || chr(10) || coalesce(text, '') || chr(10) || '<|end|>' || chr(10) AS part,
                          coalesce('r' || role, 'n') || chr(1) || coalesce('t' || text, 'n') || chr(2) AS content FROM conversations),
        p AS (SELECT conv_id, place, string_agg(content, '') OVER (PARTITION BY conv_id ORDER BY place) AS prefix, count(*) OVER (PARTITION BY conv_id) AS n_turns FROM t),
        w AS (SELECT prefix, min(conv_id) AS conv_id, min(n_turns) AS n_turns, count(*) AS n_copies FROM p WHERE place = n_turns GROUP BY prefix),
        k AS (SELECT * FROM w WHERE prefix NOT IN (SELECT prefix FROM p WHERE place < n_turns))
        SELECT k.conv_id, k.n_turns, k.n_copies, string_agg(t.part, '' ORDER BY t.place) AS rendered
        FROM k JOIN t USING (conv_id) GROUP BY ALL""",
    "op7_warc": """
        WITH p AS (SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha256(coalesce(html, '')) AS payload_digest FROM pages),
        f AS (SELECT *, min(page_id) OVER (PARTITION BY payload_digest) AS first_id FROM p)
        SELECT page_id, payload_bytes, payload_digest,
               CASE WHEN payload_bytes >= 100 AND page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
               CASE WHEN payload_bytes >= 100 AND page_id <> first_id THEN first_id END AS refers_to
        FROM f""",
    "op10_quality_rules": r"""
        WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
        w AS (SELECT doc_id, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS ws,
                     list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls,
                     regexp_split_to_array(lower(t), '[^\pL]+') AS ts FROM d),
        g AS (SELECT doc_id, i, array_to_string(ws[i:i+4], ' ') AS k FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 3)) AS i FROM w)),
        r AS (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, k) AS c FROM g),
        v AS (SELECT doc_id, count(DISTINCT i + j) AS n FROM r, range(5) AS o(j) WHERE c > 1 GROUP BY doc_id),
        m AS (SELECT w.doc_id, len(ws) AS n_words, length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g')) AS word_chars,
                     length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS n_symbols,
                     len(ls) - len(list_distinct(ls)) AS n_dup_lines, coalesce(v.n, 0) AS n_repeat_words, len(ls) AS n_lines,
                     len(list_filter(ls, lambda x: rtrim(x, ' ') LIKE '%...' OR rtrim(x, ' ') LIKE '%…')) AS n_ellipsis,
                     len(list_filter(ls, lambda x: regexp_matches(ltrim(x, ' '), '^[-*•]'))) AS n_bullet,
                     len(list_filter(ws, lambda x: regexp_matches(x, '\pL'))) AS n_letter,
                     len(list_filter(ts, lambda x: list_contains([{stop}], x))) AS n_stop
              FROM w LEFT JOIN v USING (doc_id)),
        b AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m)
        SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols,
               n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words::BIGINT AS n_repeat_words, base_failed,
               NOT base_failed AND word_chars BETWEEN 1.5 * n_words AND 14 * n_words AND n_symbols <= 0.25 * n_words
               AND n_dup_lines <= 0.3 * n_lines AND n_ellipsis <= 0.5 * n_lines AND n_bullet <= 0.9 * n_lines
               AND n_letter >= 0.6 * n_words AND n_stop >= 0.01 * n_words AS kept
        FROM b""".replace(r"\\", "\\").replace("{stop}", ", ".join(f"'{w}'" for w in sorted({w for words in quality.STOP_WORDS.values() for w in words}))),
}
