"""The corpus pipeline: stages over documents, each written and read again by its caller.

toxicity, n-gram Jaccard join, secret scan and source mixing return the columns of
documents; the last stage encodes what is left.  No stage fails on nulls in any column,
empty or very long texts, repeated rows, further columns (of any name; they are not
carried on) or empty tables; what each makes of them stands in its docstring.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from pathlift.llm.frames import Workspace, held_out, table
from pathlift.llm.mixing import mix_documents
from pathlift.llm.ngram_join import similar_groups
from pathlift.llm.pieces import encode_documents, load_pieces
from pathlift.llm.queries import PIECE_MODEL
from pathlift.llm.secret_scan import scan_secrets
from pathlift.llm.toxicity import fit_toxicity, score_toxicity

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model does not reject; labels of the held-out quarter teach nothing.

    Null and empty texts hold no toxic word and stay, as do rows without an id; repeated
    rows share their fate.  Without labels nothing is rejected.
    """
    labels = table(spark, sf_dir, "labels").select("doc_id", "toxic").where(~held_out())
    model = fit_toxicity(docs.select("doc_id", "text"), labels)
    return score_toxicity(docs.select(*COLUMNS), model).where("predicted = 0").select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the one with the smallest id, of each group of near copies (5 words, 0.8).

    Rows that repeat an id count as one document, whose first row by text and then by the
    other columns stays; documents without an id and those without words stay.
    """
    groups = similar_groups(docs.select("doc_id", "text"), words=5, percent=80)
    kept = groups.where("doc_id = component_id").select("doc_id").distinct()
    first = F.row_number().over(Window.partitionBy("doc_id").orderBy("text", "lang", "source", "n_chars"))
    named = docs.select(*COLUMNS).join(kept, "doc_id").withColumn("place", first).where("place = 1").drop("place")
    return named.unionByName(docs.where(F.col("doc_id").isNull()).select(*COLUMNS)).select(*COLUMNS)


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document, with the secrets of its text (nested encodings too) replaced by a mark.

    A null text stays null with the n_chars that it had; elsewhere n_chars is counted anew.
    """
    found = scan_secrets(docs.select(*COLUMNS), redacted_col="text")
    return found.withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars"))).select(*COLUMNS)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents drawn so that sources, languages and topics near their target shares.

    The stage keeps all but a twentieth of the tokens: it trims what is over target.
    Null sources and languages are a value of their own; documents without words stay;
    repeated rows are drawn together, rows without an id by their text.
    """
    mixed = mix_documents(docs.select(*COLUMNS), budget_share=0.95)
    return mixed.where("sampled OR n_tokens = 0").select(*COLUMNS)


def encode_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of every document with the scores of its best segmentations.

    They are written here, in small Arrow batches, so that texts and ids of few
    documents at a time are in memory.  Null and empty texts have no pieces; repeated rows
    encode alike.
    """
    encoded = encode_documents(docs.select("doc_id", "text", "lang", "source"), load_pieces(PIECE_MODEL), ids="best", cache_words=120_000)
    return Workspace(spark, "pieces").keep(encoded.select("doc_id", "lang", "source", "n_pieces", "ids", "nbest_scores", "nbest_digests", "decoded"), "encoded")


STAGES = [
    ("toxicity", drop_toxic),
    ("n-gram Jaccard join", drop_near_copies),
    ("secret scans", redact_secrets),
    ("mixing sources", mix_sources),
    ("sentencepiece encoding", encode_pieces),
]
#: A learned model and an iterative join have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages in order to documents; all but the last are written and read again."""
    docs, work = table(spark, sf_dir, "documents"), Workspace(spark, "pipeline")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = work.keep(docs, f"stage-{k}", release=True)
            work.forget_all_but(f"stage-{k}")
    return docs
