"""Five stages from raw documents to a weighted training corpus. Each stage's result is a Parquet table that the next one reads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from suffix_engine.llm import decontaminate, lines, mixing, ngram_join, quality
from suffix_engine.session import discard, new_path, release, scratch


def _free(name: str, docs: DataFrame) -> str:
    """A name that no column has."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops what the quality classifier rejects. Null and empty texts score as texts without features do; repeated rows stay or go together."""
    model = quality.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    score = _free("score", docs)
    return quality.with_score(docs, model, score=score).where(F.col(score) >= 0.5).select(docs.columns)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops lines that three documents or more share, but for the last; n_chars follows the text. A null text becomes an empty one; each
    row counts as a document. A document all of whose lines went stays, with an empty text."""
    rest = tuple(c for c in docs.columns if c not in ("doc_id", "text", "n_chars"))
    return lines.dedup_lines(docs, keep=rest).withColumn("n_chars", F.char_length("text").cast("long")).select(docs.columns)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents linked by shingles of five words at a similarity of 0.8 or more, the one with the least id stays.

    Rows with a null id come after all others, told apart by their texts. Rows with one id stay or go together, but of those that also
    have one text a single one stays. Documents without words (null, empty) are linked with nothing and stay.
    """
    key, other = _free("key", docs), _free("other", docs)
    # beyond all ids in use, and the same for equal texts
    late = F.lit(1 << 62) + F.pmod(F.xxhash64("text"), F.lit(1 << 62))
    keyed = docs.withColumn(key, F.coalesce(F.col("doc_id").cast("long"), late))
    found = ngram_join.components(keyed.select(F.col(key).alias("doc_id"), "text"), size=5, percent=80)
    copies = found.where(F.col("component_id") != F.col("doc_id")).select(F.col("doc_id").alias(other)).distinct()
    kept = keyed.join(copies, F.col(key) == F.col(other), "left_anti")
    repeated = keyed.groupBy(key).agg(F.count(F.lit(1)).alias("_n")).where("_n > 1").select(F.col(key).alias(other))
    once = kept.join(repeated, F.col(key) == F.col(other), "left_anti")
    several = kept.join(repeated, F.col(key) == F.col(other), "left_semi").dropDuplicates([key, "text"])
    return once.unionByName(several).select(docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents of which a twentieth or more is in windows of benchmark items. A null text becomes an empty one and stays."""
    return decontaminate.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def mix_domains(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Adds the rate at which each document is to be taken, on average, 0 for never, so that poor and toxic text keeps within its share of
    the tokens (mixing.AT_MOST). The rate is the decision: this stage weighs documents and drops none, as some clean ones get rate 0, too."""
    mixed = mixing.mix(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return mixed.select(*(c for c in docs.columns if c not in ("n_tokens", "rate")), "n_tokens", "rate")


STAGES = [
    ("quality", keep_quality),
    ("lines", drop_lines),
    ("near_duplicates", one_of_each_group),
    ("decontamination", drop_contaminated),
    ("mixing", mix_domains),
]

#: Learned scores decide the first and the last stage, which SQL can't express; the tests hold each stage against a plain version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages one after another. What a stage has written for itself goes when its result is stored, and that when the next one is."""
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES[:-1]:
        path = new_path(spark, name)
        with scratch(spark):
            stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        if before:
            discard(spark, before)
        before = path
        release(spark)  # of what the driver holds of the stage's plans, too
    return STAGES[-1][1](spark, docs, sf_dir)
