"""From raw documents to training tokens, stage by stage.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before it kept. All but the last return the columns
of documents; the last adds the ids of each text.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lattica.llm import mixing, near_duplicates, piece_bpe, quality, suffix_dedup
from lattica.llm.common import saved, table, tokenizer_path


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the threshold table rejects go.

    Null, empty and wordless texts fail and go; texts of any length are judged whole; repeated rows are judged alike; other
    columns, whatever their names, pass through; an empty table stays empty.
    """
    return quality.kept(docs)


def near_duplicate_join(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near duplicates one document stays, one with the least id (a null id only if all are null).

    Texts without words all stay; of rows with equal id and text one stays; rows that share an id but are no near
    duplicates don't touch each other; other columns come from the row that stays; an empty table stays empty.
    """
    return near_duplicates.kept(docs)


def repeated_strings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Strings of 200 bytes that begin at two places or more are cut out, whole characters only.

    Null, empty and short texts stay as they are; documents of which no word is left go, so of repeated rows of 200 bytes or more
    none stays (the stage before leaves none); n_chars follows the text, other columns pass through; an empty table stays empty.
    """
    return suffix_dedup.removed(docs)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources are mixed to their target weights; a document has a row for each pass that takes words of it.

    Wordless texts give nothing and go; a null source is a source of its own, the last; rows with equal or null ids are mixed one by
    one; a long text may be taken in part; n_chars follows the text, other columns pass through; an empty table stays empty.
    """
    return mixing.mixed_documents(docs)


def sentencepiece_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, ids and n_tokens.

    A null or empty text has no ids; texts of any length are encoded whole, repeated rows alike; other columns go; an empty table
    stays empty.
    """
    out = piece_bpe.encoded(docs, tokenizer_path("piece_bpe_32k.model"), keep_text=False)
    return out.select("doc_id", "lang", "source", "ids", F.size("ids").cast("bigint").alias("n_tokens"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_rules", quality_rules),
    ("near_duplicate_join", near_duplicate_join),
    ("repeated_strings", repeated_strings),
    ("source_mix", source_mix),
    ("sentencepiece_ids", sentencepiece_ids),
]

#: Similarity joins by signatures, suffix sorting and seeded draws have no SQL form.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written and read again before the next."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = saved(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
