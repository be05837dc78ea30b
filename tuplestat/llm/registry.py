"""Queries of the training-data operators, with SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import (
    cotrain_quality,
    decontaminate,
    passage_dedup,
    piece_codec,
    secret_grammar,
    segment_topk,
    sketch_dedup,
    token_counts,
    token_store,
    weak_toxicity,
)
from .shared import staged_path


def tokenizer_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_sketch_dedup(spark, sf_dir):
    return sketch_dedup.near_duplicates(table(spark, sf_dir, "documents"), size=2, percent=80)


def op2_cotrain_quality(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return cotrain_quality.cotrained(docs, table(spark, sf_dir, "labels"))


def op3_secret_scan(spark, sf_dir):
    return secret_grammar.secret_scan(table(spark, sf_dir, "documents"))


def op4_passage_dedup(spark, sf_dir):
    return passage_dedup.repeated_passages(table(spark, sf_dir, "documents"))


def op5_segment_topk(spark, sf_dir):
    return segment_topk.top_k(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0, k=10, scale=1024)


def op6_token_store(spark, sf_dir):
    path = staged_path(spark, "tokens")  # goes away with the session
    token_store.write_tokens(table(spark, sf_dir, "documents"), path, tokenizer_file("word_bpe_49k.json"), end_id=1)
    return token_store.read_tokens(spark, path)


def op7_token_counts(spark, sf_dir):
    return token_counts.token_counts(table(spark, sf_dir, "documents"), tokenizer_file("piece_bpe_32k.model"))


def op8_decontaminate(spark, sf_dir):
    found = decontaminate.decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), n=10)
    return found.drop("text_hash", "spans")


def op9_piece_codec(spark, sf_dir):
    return piece_codec.piece_codec(table(spark, sf_dir, "documents"), tokenizer_file("piece_bpe_32k.model"))


def op10_weak_toxicity(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    return weak_toxicity.toxicity(docs, weak_toxicity.fit_model(docs, table(spark, sf_dir, "labels")), threshold=0.3)


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict:
    return {
        f.__name__: f
        for f in (
            op1_sketch_dedup,
            op2_cotrain_quality,
            op3_secret_scan,
            op4_passage_dedup,
            op5_segment_topk,
            op6_token_store,
            op7_token_counts,
            op8_decontaminate,
            op9_piece_codec,
            op10_weak_toxicity,
            pipeline,
        )
    }


OP1_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, [x for x in regexp_split_to_array(
    translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[\x20\x09-\x0D]+') if x <> ''] AS w
  FROM documents
), s AS (
  SELECT DISTINCT doc_id, sh FROM (
    SELECT doc_id, CASE WHEN len(w) = 1 THEN [w[1]] ELSE [w[i], w[i + 1]] END AS sh
    FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w), 2))) AS i FROM w WHERE len(w) > 0))
), n AS (SELECT doc_id, count(*) AS k FROM s GROUP BY doc_id
), e AS (
  SELECT p.a, p.b FROM (
    SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS both
    FROM s x JOIN s y ON x.sh = y.sh AND x.doc_id < y.doc_id GROUP BY 1, 2) p
  JOIN n na ON na.doc_id = p.a JOIN n nb ON nb.doc_id = p.b
  WHERE 100 * p.both >= 80 * (na.k + nb.k - p.both)
), u AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e
), r AS (
  SELECT doc_id AS id, doc_id AS node FROM documents
  UNION
  SELECT r.id, u.b FROM r JOIN u ON r.node = u.a
), c AS (SELECT id, min(node) AS component_id FROM r GROUP BY id)
SELECT d.doc_id, CAST(coalesce(n.k, 0) AS BIGINT) AS n_shingles, c.component_id, d.doc_id = c.component_id AS kept
FROM documents d JOIN c ON c.id = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id
"""

OP5_SQL = """
WITH v AS (
  SELECT vec_id, [CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT) for x in embedding] AS e
  FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len([x for x in embedding if x IS NULL OR NOT isfinite(x)]) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
         CAST(list_sum([p[1] * p[2] for p in list_zip(q.e, c.e, true)]) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id
  WHERE q.vec_id % 100 = 0
), r AS (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rk FROM s
)
SELECT query_id, CAST(rk AS INTEGER) AS rank, vec_id, score FROM r WHERE rk <= 10
"""

OP8_SQL = r"""
WITH d AS (
  SELECT doc_id, [w for w in regexp_split_to_array(
    translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[\x00-\x2F\x3A-\x60\x7B-\x7F]+') if w <> ''] AS w
  FROM documents
), b AS (
  SELECT item_id, [w for w in regexp_split_to_array(
    translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'),
    '[\x00-\x2F\x3A-\x60\x7B-\x7F]+') if w <> ''] AS w
  FROM benchmark
), bw AS (
  SELECT DISTINCT item_id, size, w[p : p + size - 1] AS words
  FROM (SELECT item_id, w, size, unnest(range(1, len(w) - size + 2)) AS p
        FROM (SELECT item_id, w, least(len(w), 10) AS size FROM b WHERE len(w) > 0))
), dw AS (
  SELECT doc_id, p, size, w[p : p + size - 1] AS words
  FROM (SELECT doc_id, w, size, unnest(range(1, len(w) - size + 2)) AS p
        FROM d, (SELECT DISTINCT size FROM bw) WHERE len(w) >= size)
), hit AS (
  SELECT dw.doc_id, dw.p, dw.size, bw.item_id FROM dw JOIN bw ON dw.words = bw.words AND dw.size = bw.size
), places AS (
  SELECT doc_id, count(DISTINCT place) AS n_hit
  FROM (SELECT doc_id, unnest(range(p, p + size)) AS place FROM hit) GROUP BY doc_id
), named AS (
  SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items
  FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS item FROM hit WHERE item_id IS NOT NULL) GROUP BY doc_id
)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit,
       CAST(coalesce(n_items, 0) AS BIGINT) AS n_items, sha256(coalesce(items, '')) AS items_sha256,
       coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN places USING (doc_id) LEFT JOIN named USING (doc_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_sketch_dedup": OP1_SQL, "op5_segment_topk": OP5_SQL, "op8_decontaminate": OP8_SQL}
