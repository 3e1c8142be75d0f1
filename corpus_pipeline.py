"""The corpus pipeline: five filtering and encoding stages over ``documents``, each written and read again.

Every stage takes (spark, docs, sf_dir) and works on all that its predecessor kept; all but the last return the columns of documents.  Further columns,
of whatever name, pass through them.  Null or empty texts and null ids stay in every filtering stage; empty tables stay empty.
"""

from __future__ import annotations

from planepack.llm import common, decontam, jaccard, pieces, secrets, toxicity
from planepack.storage import passing


def drop_toxic(spark, docs, sf_dir):
    """Documents that the classifier chain rejects go; the chain is fitted on a bounded sample of this stage's labelled rows.

    Rows with null or empty text stay; repeated rows are judged alike; without labels nothing is rejected.
    """
    return toxicity.score(docs, toxicity.fit_chain(docs, common.table(spark, sf_dir, "labels")), filtering=True)


def drop_near_copies(spark, docs, sf_dir):
    """One document of each group of near-duplicates stays: five-word shingles, similarity 0.8.

    The one with the smallest id stays, nulls last; of repeated rows one; rows without words all stay.
    """
    return jaccard.drop_near_duplicates(docs, n=5, num=80, den=100)


def decontaminate(spark, docs, sf_dir):
    """Benchmark passages are cut out; documents that are mostly benchmark go.  Null and empty texts stay; repeated rows are treated alike."""
    return decontam.remove_spans(docs, common.table(spark, sf_dir, "benchmark", "item_id", "text"))


def redact_secrets(spark, docs, sf_dir):
    """Secrets are replaced by marks; every document stays, null texts as null, repeated rows as often as they came."""
    return secrets.redact(docs)


def encode(spark, docs, sf_dir):
    """Sampled piece ids of every document: doc_id, n_pieces, ids, lossless.  A null text has null ids and 0 pieces; equal ids and texts get equal pieces."""
    return pieces.encode(docs)


STAGES = [("toxicity", drop_toxic), ("near_duplicates", drop_near_copies), ("decontamination", decontaminate), ("secrets", redact_secrets), ("sentencepiece", encode)]


def run(spark, sf_dir):
    """The rows of the last stage.  What a stage writes on its way, and its predecessor's rows, are deleted once its own rows are written."""
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        keep: list[str] = []
        with passing(spark, keep):
            out = common.written(stage(spark, docs, sf_dir), name)
            keep.append(out._pp_path)
        if hasattr(docs, "_pp_path"):
            common.forget(docs)
        docs = out
    return STAGES[-1][1](spark, docs, sf_dir)


#: Several stages (a trained model, the join, sampling) have no SQL form; tests/llm/test_pipeline.py holds each against a plain Python version.
ORACLE_SQL = None
