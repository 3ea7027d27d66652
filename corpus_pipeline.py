"""A corpus from raw documents to token ids: five stages, each written as Parquet and read again by the next.

1. toxicity: documents that the classifier rejects go;
2. near-duplicates: of each group at five-word shingles and 0.8 similarity the smallest doc_id stays;
3. decontamination: documents with a passage of the benchmark go;
4. mixing: domains, languages and sources to target weights, each document at most once;
5. token ids: written in the shard format in ascending doc_id order and read back.

Cases, of every stage but the last: all columns of ``docs`` come back, whatever their names. Null, empty and wordless
texts pass the first three stages (they score like a text without known words, link with nothing, hold no passage) and
have no tokens, so mixing leaves them out. Rows that share a doc_id are judged one by one for toxicity and passages, and
are one document among near-duplicates; equal rows are mixed in together or not at all. A null doc_id is kept. Empty
tables, no labels or no benchmark drop nothing; an empty table of documents gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from semrank.llm import decontaminate, mixing, near_dedup, token_files, toxicity
from semrank.llm.common import new_path, table

#: The share of the remaining tokens that the mixture asks for, and the seed of its order.
MIX_SHARE, MIX_SEED = 0.8, 42


def _free(docs: DataFrame, name: str) -> str:
    """A beginning of names that no column of ``docs`` has."""
    while any(c.lower().startswith(name) for c in docs.columns):
        name = "_" + name
    return name


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Learns from the labelled documents that reach this stage; keeps those that score below the threshold."""
    model = toxicity.learn(docs, table(spark, sf_dir, "labels"))
    score = _free(docs, "toxic_score")
    return toxicity.with_scores(docs, model, score).filter(F.col(score) < toxicity.THRESHOLD).drop(score)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return near_dedup.one_per_group(docs, width=5, percent=80)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    leak = _free(docs, "leak_")
    found = decontaminate.find_leaks(docs, table(spark, sf_dir, "benchmark"), prefix=leak)
    return found.filter(F.col(f"{leak}n_hit") == 0).select(*(F.col(f"`{c}`") for c in docs.columns))


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed_documents(docs, F.sum("tokens") * MIX_SHARE, seed=MIX_SEED, domain_weights=mixing.DOMAIN_WEIGHTS, lang_weights=mixing.LANG_WEIGHTS)


def write_tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return token_files.token_round_trip(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("near_dedup", drop_near_copies),
    ("decontaminate", drop_contaminated),
    ("mixing", mix),
    ("token_files", write_tokens),
]

#: The classifier and the tokenizer can't be written in SQL; tests/llm hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    path = new_path(spark, "pipeline")
    for number, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        out.write.parquet(f"{path}/{number}-{name}")
        docs = spark.read.schema(out.schema).parquet(f"{path}/{number}-{name}")
    return docs
