"""A corpus pipeline of five operators; each stage is written and reread as the next one's input."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from matchloom.catalog import load
from matchloom.llm import bpe, langid, mixing, simhash, toxicity
from matchloom.llm.queries import vocabulary
from matchloom.llm.storage import Scratch

#: A text stays if its language has at least this share of its words' label mass.
LEAST_LANGUAGE_SCORE = 0.4


def free_name(docs: DataFrame, name: str) -> str:
    """``name``, made longer until no column of the documents is called so."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name += "_"
    return name


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier, trained on all labelled ones, scores below its threshold."""
    model = toxicity.train(docs, load(spark, sf_dir, "labels"))
    score = free_name(docs, "toxicity_score")
    scored = toxicity.score_documents(docs, model, keep=docs.columns, score_col=score)
    return scored.where(F.col(score) < toxicity.THRESHOLD).select(*docs.columns)


def keep_known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in one of the labelled languages; texts without letters and texts that no
    language dominates go. Without any labelled language nothing can be rejected."""
    model = langid.train(docs, learn=F.lit(True))
    if not model.labels:
        return docs
    lang, score = free_name(docs, "read_lang"), free_name(docs, "read_score")
    read = langid.predict_documents(docs, model, keep=docs.columns, names=(lang, score))
    return read.where((F.col(lang) != langid.UNKNOWN) & (F.col(score) >= LEAST_LANGUAGE_SCORE)).select(*docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of similar documents (five-word shingles, Jaccard 0.8) that with the
    smallest id; rows with a null id stay. Of rows that share an id the first in order of text
    is judged, and kept if the document is."""
    scratch = Scratch(spark, "dedup")
    counts = docs.agg(F.count("doc_id"), F.countDistinct("doc_id")).first()
    if counts[0] != counts[1]:
        row = F.struct(*docs.columns)
        known = docs.where("doc_id is not null").groupBy("doc_id").agg(F.min_by(row, F.struct("text", row.cast("string"))).alias("doc"))
        docs = scratch.save(known.select("doc.*").unionByName(docs.where("doc_id is null")), "once")
    parts = simhash.similar_documents(docs, shingle=5, similarity=0.8, scratch=scratch)
    gone = scratch.save(parts.where("doc_id <> component_id").select("doc_id"), "gone")
    scratch.drop_others(docs, gone)
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents of the mix: a row for each turn in which a document is taken."""
    return mixing.mixed_documents(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each mixed document, as count and digest, with the decoded text's digest."""
    return bpe.encode_documents(docs, vocabulary("byte_bpe_50k.json"))


STAGES = [
    ("toxicity", drop_toxic),
    ("language_id", keep_known_languages),
    ("simhash_near_dedup", drop_near_duplicates),
    ("mixing", mix_sources),
    ("bpe", encode),
]

#: Classifiers, fingerprints and tokenisers have no SQL form; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each stage's rows written and reread."""
    scratch = Scratch(spark, "pipeline")
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
