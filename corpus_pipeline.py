"""A corpus pipeline of five stages, each written as Parquet and read again by the next.

toxicity -> near-duplicates -> benchmark decontamination -> secrets -> sentencepiece ids. The
first four return the columns of `documents`; stages that filter drop what they reject, the
secrets stage masks spans and keeps the documents, and the last returns the ids.

All stages: only id, text and (where there) n_chars are read or written, and other columns of any name
pass through, clashing ones too; a null or empty text is a text without words; an empty table gives an
empty one. Each docstring adds what its stage does with null ids, ties and repeated rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tuplestat import workers_find_us
from tuplestat.llm import decontaminate, piece_codec, secret_grammar, sketch_dedup, weak_toxicity
from tuplestat.llm.registry import tokenizer_file
from tuplestat.llm.shared import fresh, staged
from tuplestat.operators.samples import number_rows

ORACLE_SQL = None  # a learnt score decides the first stage

TOXIC_FROM = 0.3


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score stays below the threshold; one scan, no shuffle.

    A score equal to the threshold is rejected. Null and empty texts have the score of a text without
    evidence; rows with a null id are scored and kept alike, and so is each of a row's repeats. Texts
    of any length are scored whole. Without usable labels of both classes nothing can be told apart
    and every score is the known share of toxic rows (0 without labels: all rows stay)."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = weak_toxicity.fit_model(docs, labels)
    score = fresh(docs.columns, "toxicity_score")
    return (
        docs.withColumn(score, weak_toxicity.score_column(F.col("text"), model, spark))
        .where(F.col(score) < TOXIC_FROM)
        .drop(score)
    )


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates (five-word shingles, 0.8): the smallest id.
    Of rows that repeat an id, each text is a document of its own, and one row stays for each text.
    Rows with a null id all stay."""
    again = docs.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1")
    if again.isEmpty():
        return _without_copies(docs, "doc_id")
    # Rows are numbered by id and text, in the order of ids; only tables with repeated ids pay for it.
    row, text = (fresh(docs.columns, c) for c in ("row_id", "text_key"))
    hashed = docs.withColumn(text, F.coalesce(F.sha2("text", 256), F.lit("")))
    named = hashed.where("doc_id IS NOT NULL")
    keys = named.select(F.lit(0).alias("sample"), F.struct("doc_id", text).alias("key")).distinct()
    numbers = number_rows(keys).select("key.*", F.col("idx").alias(row))
    kept = _without_copies(named.join(numbers, ["doc_id", text]).dropDuplicates([row]), row)
    return kept.select(*docs.columns).union(docs.where("doc_id IS NULL"))


def _without_copies(docs: DataFrame, id_col: str) -> DataFrame:
    found = sketch_dedup.near_duplicates(docs, size=5, percent=80, id_col=id_col)
    gone = found.where(~F.col("kept")).select(F.col("doc_id").alias("gone_id")).distinct()
    return docs.join(gone, docs[id_col] == gone["gone_id"], "left_anti")


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no ten-word window of a benchmark item.

    Null and wordless texts and items hold no window; a null id is compared like any other; repeated
    rows go or stay together; with an empty benchmark all rows stay; long texts are scanned whole."""
    return decontaminate.drop_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, secrets masked in the text; n_chars follows the text where it changed.

    Null texts stay null and empty ones empty; null ids and repeated rows are kept as they are;
    overlapping secrets become one mark."""
    columns = docs.columns
    clean = fresh(columns, "clean_text")
    out = docs.withColumn(clean, secret_grammar.redact(F.col("text")))
    changed = ~F.col(clean).eqNullSafe(F.col("text"))
    if "n_chars" in columns:
        out = out.withColumn("n_chars", F.when(changed, F.char_length(F.col(clean))).otherwise(F.col("n_chars")).cast("long"))
    return out.withColumn("text", F.col(clean)).select(*columns)


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids_crc32, n_off_parity, round_trip and ids of all documents.

    Null and empty texts have no ids; null ids are kept and repeated rows each give a row; other
    columns are left behind."""
    return piece_codec.piece_codec(docs, tokenizer_file("piece_bpe_32k.model"), with_ids=True)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", drop_benchmark),
    ("secrets", mask_secrets),
    ("sentencepiece", encode_pieces),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`, through Parquet in the shared folder (deleted with the session)."""
    workers_find_us(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
