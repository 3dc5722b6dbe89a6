"""From raw documents to token ids: quality rules, near-duplicate groups, repeated passages, source mix, encoding.

Each stage takes (spark, docs, sf_dir) and works on all rows that the one before kept; all but the last return
the columns of documents, whatever they are named. n_chars follows the text.

A row goes through its operator whole: its columns are numbered, so no name can clash with a result's, and the operator hands each of them
on, the text as the one copy that it reads. So a verdict is that row's own: rows with a null id, or one that other rows have too, are judged each by itself. Null texts have no words and fail the
quality rules. Of equal rows, near_duplicates keeps one. Empty tables stay empty.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.functions.session import scratch_path
from tidegraph.llm import ngram_join, pareto_mix, robust_quality, sentence_pieces, substring_dedup

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
BATCH = 4_000_000  # bytes of an Arrow batch
BATCH_SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


def in_small_batches(stage):
    """The stage, with Arrow batches of BATCH bytes instead of Spark's 64 MB: an executor and its Python workers hold one or two of each
    running task. It is the session's setting, as plans are made when a result is written; a smaller one is left. Results do not depend on it."""

    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        size = spark.sparkContext._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(BATCH_SETTING))
        if size <= 0 or size > BATCH:
            spark.conf.set(BATCH_SETTING, str(BATCH))
        return stage(spark, docs, sf_dir)

    return run


def numbered(docs: DataFrame) -> tuple[DataFrame, dict[str, str], tuple[str, ...]]:
    """The columns as c0, c1 ..., what each is now called, and all of these names but the id's."""
    at = {c: f"c{i}" for i, c in enumerate(docs.columns)}
    return docs.select(*[F.col(f"`{c}`").alias(n) for c, n in at.items()]), at, tuple(n for c, n in at.items() if c != "doc_id")


def named(rows: DataFrame, at: dict[str, str], **changed) -> DataFrame:
    return rows.select(*[changed.get(c, F.col(n)).alias(c) for c, n in at.items()])


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or the outlier test reject go."""
    rows, at, others = numbered(docs)
    return named(robust_quality.judge(rows, at["doc_id"], at["text"], at["lang"], at["source"], keep=others).where("kept"), at)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays, that with the least id. Five-word shingles, similarity of 0.8."""
    rows, at, others = numbered(docs)
    return named(ngram_join.similar_groups(rows, at["doc_id"], at["text"], k=5, percent=80, keep=others).where("first"), at)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages of 20 words or more that occur earlier are cut out; a text without any stays as it was, one of nothing else goes."""
    rows, at, others = numbered(docs)
    marked = substring_dedup.mark_repeats(rows, at["doc_id"], at["text"], keep=others).where("n_removed = 0 or n_removed < n_words")
    cut_out = F.col("n_removed") > 0
    changed = {"text": F.when(cut_out, F.col("kept_text")).otherwise(F.col(at["text"]))}
    if "n_chars" in at:
        changed["n_chars"] = F.when(cut_out, F.length("kept_text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col(at["n_chars"]))
    return named(marked, at, **changed)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    rows, at, others = numbered(docs)
    taken = pareto_mix.mix(rows, at["doc_id"], at["text"], at["source"], keep=others).where("copies > 0")
    return named(taken.select(*at.values(), F.explode(F.sequence(F.lit(1), F.col("copies").cast("int")))), at)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, lang, source, n_tokens, ids, and round_trip: whether the ids decode to the text (false only where it holds U+2581)."""
    return sentence_pieces.encode(docs, MODEL, keep=("doc_id", "lang", "source"))


STAGES = [("quality rules", quality), ("n-gram jaccard join", near_duplicates), ("substring dedup", repeated_passages), ("source mix", source_mix), ("piece encoding", encode)]
STAGES = [(name, in_small_batches(stage)) for name, stage in STAGES]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    base = scratch_path(spark, "pipeline")
    for k, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k == len(STAGES) - 1:
            return out
        out.write.parquet(f"{base}/{k}")
        docs = spark.read.parquet(f"{base}/{k}")
    return docs


ORACLE_SQL = None  # several stages have no SQL form; tests/llm holds run() against a plain version
