"""A training corpus from `documents` in five stages: toxicity, exact copies, near copies, mix of sources, encoding.

Each stage takes (spark, docs, sf_dir) and works on all rows that the stage before kept; all but the last return the columns
of `documents`. Between stages the rows are written as Parquet and read again.

Null and empty texts are not toxic, count as equal to each other in exact dedup, have no near copies, and are not taken by the
mix (they have no words). Rows of null id stay in the dedup stages unless their text is equal to another row's. Rows
that repeat an id and a text share their verdict; ties go to the largest id in exact dedup and to the least in near dedup. Empty tables give empty results. Further
columns, also such as the stages use inside, come through to the mix.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hyperembed.llm import exact_dedup, mixing, ngram_join, sentence_pieces, toxicity
from hyperembed.llm.common import give_back_driver, give_back_executors, stash, table
from hyperembed.llm.queries import vocabulary


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the weakly supervised classifier does not mark as toxic. It learns from labelled rows among `docs`."""
    model = toxicity.learn(docs, table(spark, sf_dir, "labels"))
    return toxicity.score(docs, model, carry=True).where("predicted = 0").select("_row.*")


def drop_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the largest doc_id."""
    return exact_dedup.keep_one(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near copies the row with the least doc_id."""
    return ngram_join.one_of_each_class(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it."""
    return mixing.mixed_documents(docs)


def encode_samples(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sampled segmentations of each row: (doc_id, sample, n_tokens, ids, log_prob, perturbed, inclusion)."""
    return sentence_pieces.sample_segmentations(docs, vocabulary("piece_bpe_32k.model"))


STAGES = [
    ("toxicity", drop_toxic), ("exact dedup", drop_copies), ("n-gram Jaccard join", drop_near_copies),
    ("mixing sources to target weights", mix_sources), ("SentencePiece encoding and decoding", encode_samples),
]

#: The classifier and the sampler have no SQL form; tests/llm/test_pipeline.py compares the stages with brute force on a small table.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    *first, (_, last) = STAGES
    for name, stage in first:
        docs = stash(stage(spark, docs, sf_dir), "stage")
        give_back_executors(spark)
        give_back_driver(spark)
    return last(spark, docs, sf_dir)
