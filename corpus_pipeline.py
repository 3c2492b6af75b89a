"""The training-corpus pipeline: five text operators in a row over ``documents``.

Each stage takes ``(spark, docs, sf_dir)`` and returns a DataFrame; all but the
last keep the columns of ``documents``, names, order, types and contents,
whatever else they are called: the operators see ``doc_id`` and ``text``, all
other columns travel under names of their own.  ``run`` writes every stage to
the shared folder and reads it again, so a lost executor costs one stage's
tasks.

In every stage an empty table gives an empty table, other columns may hold
nulls or anything, and texts of any length are read whole.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from manifold_engine.llm import bpe, decontaminate, jaccard, linechunks, toxicity
from manifold_engine.llm.queries import table, vocabulary_path
from manifold_engine.spool import spool

SEEN = ("doc_id", "text")


def apart(docs: DataFrame, fn: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """``fn`` over ``docs`` whose columns but id and text are named so that no operator's own can clash."""
    names = {c: c if c in SEEN else f"own_{i}__" for i, c in enumerate(docs.columns)}
    out = fn(docs.select(*[F.col(f"`{c}`").alias(n) for c, n in names.items()]))
    return out.select(*[F.col(n).alias(c) for c, n in names.items()])


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored below the threshold stay.

    Null and empty texts get the score of a text that says nothing either way.
    Repeated rows and rows with equal texts share a score, so all or none stay;
    a null id is judged by its text.
    """
    labels = table(spark, sf_dir, "labels")
    return apart(docs, lambda d: toxicity.score(d, labels).where("predicted = 0"))


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document stays, less its repeated runs of lines; ``n_chars``, where there is one, follows the text.

    Null texts stay null; a text left without lines is empty.  Of equal texts
    the one with the smallest id keeps its lines (a null id ranks last); rows
    that share an id are one document and keep them together.
    """
    clean = apart(docs, linechunks.drop_repeated_chunks)
    if "n_chars" not in docs.columns:
        return clean
    kind = docs.schema["n_chars"].dataType
    return clean.select(*[F.length("text").cast(kind).alias(c) if c == "n_chars" else c for c in docs.columns])


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest id of each group of near copies stays (five words, similarity 0.8).

    Null texts, texts without words and rows without id have no copies and stay.
    Repeated rows are one document: all stay or none.
    """
    return apart(docs, lambda d: jaccard.keep_smallest(d, n=5, threshold=0.8))


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that share ten consecutive words with a benchmark item, or hold a shorter item whole, go.

    Null texts and texts without words stay; rows with equal texts go or stay
    together, whatever their ids.
    """
    benchmark = table(spark, sf_dir, "benchmark")
    return apart(docs, lambda d: decontaminate.drop_hits(d, benchmark, span=10))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every text, with the digests of ids and decoded text, one row for each row.

    Null counts as empty text and gives no ids; ``lang`` and ``source`` are carried.
    """
    keep = tuple(c for c in docs.columns if c in ("lang", "source"))
    return bpe.round_trip(docs, vocabulary_path(), keep=keep, with_ids=True)


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_repeated_lines),
    ("ngram_jaccard_join", drop_near_copies),
    ("benchmark_decontamination", drop_contaminated),
    ("bpe", encode),
]

#: A class-conditional model cannot be stated in SQL; tests hold each stage against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = spool(docs, name)
    return docs
