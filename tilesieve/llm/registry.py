"""Queries of the training-data operators, and their oracle SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def word_tokenizer() -> str:
    """The installed tokenizer file of the query; a path, never copied."""
    import public_tokenizers

    return str(public_tokenizers.path("word_bpe_49k.json"))


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesieve.llm.quality import score_documents, train

    docs = table(spark, sf_dir, "documents")
    return score_documents(docs, train(docs, table(spark, sf_dir, "labels")))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesieve.llm.decontam import contaminated

    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesieve.llm.jaccard import near_duplicate_classes

    return near_duplicate_classes(table(spark, sf_dir, "documents"))


def op4_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesieve.llm.secrets import find_secrets

    return find_secrets(table(spark, sf_dir, "documents"))


def op5_curriculum(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesieve.llm.curriculum import ranked_mix

    return ranked_mix(table(spark, sf_dir, "documents"))


def op6_line_chunks(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesieve.llm.linechunks import dedup_chunks

    return dedup_chunks(table(spark, sf_dir, "documents"), extend=True)


def op7_packed_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesieve.llm.bitpack import packed_documents

    return packed_documents(table(spark, sf_dir, "documents"), word_tokenizer())


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesieve.llm.toxicity import score_documents, train

    docs = table(spark, sf_dir, "documents")
    return score_documents(docs, train(docs, table(spark, sf_dir, "labels")))


def op9_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesieve.llm.shards import shard_rows

    return shard_rows(table(spark, sf_dir, "documents"), 8)


def op10_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    from tilesieve.llm.collision import nearest

    return nearest(table(spark, sf_dir, "embeddings"))


def secret_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The base counts of ``op4_secrets``, which SQL can say."""
    return op4_secrets(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex")


def mix_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes and targets of ``op5_curriculum`` by document, and whether its source's takings come within one document."""
    from pyspark.sql import Window
    from pyspark.sql import functions as F

    from tilesieve.llm.curriculum import plan_mix

    docs = table(spark, sf_dir, "documents")
    per = plan_mix(docs, payload=True).withColumn("source", F.col("row.source"))
    taken = per.groupBy("source").agg(F.sum("taken").alias("t"), F.max("size").alias("most"), F.max("target").alias("g"))
    near = taken.select("source", (F.abs(F.col("t") - F.col("g")) <= F.col("most")).alias("near"))
    out = per.join(F.broadcast(near), per["source"].eqNullSafe(near["source"]))  # a row for each source
    return out.select("doc_id", "size", "source_size", F.round("target", 3).alias("target"), "near")


def shard_law(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of ``op9_shards``, and whether its law holds of all shards."""
    from pyspark.sql import functions as F

    out = op9_shards(spark, sf_dir)
    per = out.groupBy("shard").agg(F.count("*").alias("rows"), F.min("slot").alias("first"), F.max("slot").alias("last"), F.count_distinct("slot").alias("slots"))
    fits = per.select("shard", ((F.col("first") == 0) & (F.col("last") == F.col("rows") - 1) & (F.col("slots") == F.col("rows"))).alias("gapless"), "rows")
    even = fits.agg(F.count("*").alias("shards"), (F.max("rows") - F.min("rows") <= 1).alias("even"), F.bool_and("gapless").alias("gapless"))
    return out.select("doc_id", "size").crossJoin(F.broadcast(even))  # one row


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_quality": op1_quality,
        "op2_decontaminate": op2_decontaminate,
        "op3_jaccard_join": op3_jaccard_join,
        "op4_secrets": op4_secrets,
        "op5_curriculum": op5_curriculum,
        "op6_line_chunks": op6_line_chunks,
        "op7_packed_ids": op7_packed_ids,
        "op8_toxicity": op8_toxicity,
        "op9_shards": op9_shards,
        "op10_nearest": op10_nearest,
        "secret_counts": secret_counts,
        "mix_targets": mix_targets,
        "shard_law": shard_law,
    }


#: Words of a text, A to Z in lower case.
_WORDS = r"regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+')"

_JACCARD = f"""
WITH RECURSIVE w AS (SELECT doc_id, {_WORDS} AS w FROM documents),
s AS (SELECT doc_id, unnest(CASE WHEN len(w) < 4 THEN [array_to_string(w, ' ')] ELSE list_distinct(list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i : i + 3], ' '))) END) AS g FROM w WHERE len(w) > 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
e AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
u AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
r AS (SELECT doc_id AS a, doc_id AS b FROM documents UNION SELECT r.a, u.b FROM r JOIN u ON u.a = r.b)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, m.c AS component_id FROM documents d LEFT JOIN n USING (doc_id) JOIN (SELECT a AS doc_id, min(b) AS c FROM r GROUP BY a) m USING (doc_id)
"""

_ASSIGN = r"""(?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["'']?\x20*[:=]\x20*["'']?([A-Za-z0-9+/_.=-]+)"""

_SECRETS = f"""
SELECT doc_id, len(list_filter(regexp_extract_all(coalesce(text, ''), '{_ASSIGN}', 1), lambda x: length(x) >= 6))::BIGINT AS n_assign,
  len(list_filter(regexp_extract_all(coalesce(text, ''), 'AKIA[A-Z0-9]+'), lambda x: length(x) >= 20))::BIGINT AS n_access,
  len(list_filter(regexp_extract_all(coalesce(text, ''), '[0-9a-f]+'), lambda x: length(x) >= 24))::BIGINT AS n_hex FROM documents
"""

#: Stopped sources are known once a further one would not stop: targets by trying every number of stopped ones.
_TARGETS = r"""
WITH z AS (SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::BIGINT AS size FROM documents),
p AS (SELECT source, sum(size)::BIGINT AS source_size, 3.0::DOUBLE * sum(size)::DOUBLE AS cap, ([1.0, 2.0, 3.0])[((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::INT]::DOUBLE AS weight FROM z GROUP BY source),
o AS (SELECT *, cap / weight AS stop, sum(source_size) OVER ()::DOUBLE AS total, sum(weight) OVER () AS weights, row_number() OVER (ORDER BY cap / weight, source NULLS LAST) AS k FROM p),
l AS (SELECT *, (total - coalesce(sum(cap) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) / (weights - coalesce(sum(weight) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS level FROM o),
f AS (SELECT min_by(level, k) AS level FROM l WHERE level <= stop)
SELECT doc_id, size, source_size, round(CASE WHEN source_size = 0 THEN 0 ELSE least(cap, coalesce((SELECT level FROM f), stop) * weight) END, 3)::DOUBLE AS target, true AS near FROM z JOIN l ON z.source IS NOT DISTINCT FROM l.source
"""


def oracle_sql() -> dict[str, str]:
    """Whole results where SQL can say them; of the others, what it can say of them, under names of their own."""
    law = "SELECT doc_id, coalesce(strlen(text), 0)::BIGINT + 1 AS size, 8::BIGINT AS shards, true AS even, true AS gapless FROM documents"
    return {"op3_jaccard_join": _JACCARD, "secret_counts": _SECRETS, "mix_targets": _TARGETS, "shard_law": law}
