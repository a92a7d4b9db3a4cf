"""The corpus pipeline: toxicity, near-duplicates, benchmark passages, secrets, packing.

Every stage works on all that its predecessor kept; ``run`` writes each stage's rows to the shared folder and reads them again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ucqlearn.llm.common import Workspace, few_files, row_count, table
from ucqlearn.llm.components import components
from ucqlearn.llm.decontaminate import decontaminate
from ucqlearn.llm.neardup import near_duplicates
from ucqlearn.llm.packing import pack
from ucqlearn.llm.secrets import scan_secrets
from ucqlearn.llm.similar import similar_groups
from ucqlearn.llm.toxicity import score_toxicity, train_toxicity

TOXIC_FROM = 0.4


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a toxicity score of ``TOXIC_FROM`` or more go."""
    model = train_toxicity(spark, docs, table(spark, sf_dir, "labels"))
    scored = score_toxicity(spark, docs, model)
    return scored.where(F.col("score") < TOXIC_FROM).select("row.*")


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are linked by operator 10, whose fingerprints differ in 3 bits at most, and by a similarity of 0.8 on five-word shingles,
    which goes on where fingerprints don't reach. Of each group the smallest doc_id stays; rows without doc_id all stay."""
    rows = row_count(docs)
    found = [near_duplicates(spark, docs).select("doc_id", "component_id"), similar_groups(spark, docs.select("doc_id", "text"), similarity=0.8, width=5)]
    links = [g.where("component_id <> doc_id").select(F.col("doc_id").alias("u"), F.col("component_id").alias("v")) for g in found]
    others = components(links[0].union(links[1]), Workspace(spark, "near"), rows).where("component <> node").select(F.col("node").alias("doc_id")).distinct()
    return few_files(docs.join(others, "doc_id", "left_anti").select(docs.columns), rows, 10_000)


def _with_text(row: DataFrame, columns: list[str], text) -> DataFrame:
    changed = {"text": text.alias("text"), "n_chars": F.char_length(text).cast("long").alias("n_chars")}
    return row.select(*[changed.get(c, F.col(f"row.`{c}`").alias(c)) for c in columns])


def cut_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words in an occurrence of a benchmark window go, with what lies between them; documents stay unless no word is left."""
    found = decontaminate(spark, docs, table(spark, sf_dir, "benchmark"))
    left = found.where(F.col("n_hit").isin(0) | (F.col("n_hit") < F.col("n_words")))
    return _with_text(left, docs.columns, F.coalesce("cleaned", "row.text"))


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are replaced by a mark; every document stays."""
    return _with_text(scan_secrets(docs), docs.columns, F.coalesce("redacted", "row.text"))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each piece of a sequence, with its ids."""
    return pack(docs.select("doc_id", "text")).select("row.doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "sequence_tokens", "ids")


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_copies),
    ("decontamination", cut_benchmark),
    ("secrets", redact_secrets),
    ("packing", pack_sequences),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    work = Workspace(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = work.put(stage(spark, docs, sf_dir), name)
    return docs


#: Classifier, fingerprints and tokens are beyond SQL; tests compare the stages with brute force.
ORACLE_SQL = None
