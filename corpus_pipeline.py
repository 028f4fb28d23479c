"""A training-text pipeline over the documents table.

Each stage takes (spark, docs, sf_dir) and returns a frame; it is written as Parquet in the shared folder and read again as the
next stage's documents. All but the last return the columns of documents.
"""

from __future__ import annotations

import uuid

from biblake.llm import bpe, language, mixing, passages, simhash
from biblake.session import removed, shared_folder, table


def language_id(spark, docs, sf_dir):
    """Documents in which no language can be told (null text, no letter) go."""
    return language.accepted(docs)


def near_duplicates(spark, docs, sf_dir):
    """Of each group of linked fingerprints the document with the smallest id stays."""
    return simhash.one_of_each(docs)


def repeated_passages(spark, docs, sf_dir):
    """Passages that an earlier document has are cut out; a document of which nothing is left goes."""
    return passages.deduplicated(docs)


def target_weights(spark, docs, sf_dir):
    """Documents come as often as the mix takes them, not at all or up to three times."""
    return mixing.mixed_documents(docs)


def token_ids(spark, docs, sf_dir):
    """Every document's ids, with the digests of what was encoded and decoded."""
    return bpe.digest(docs)


STAGES = [
    ("language_id", language_id),
    ("near_duplicates", near_duplicates),
    ("repeated_passages", repeated_passages),
    ("target_weights", target_weights),
    ("token_ids", token_ids),
]

#: SQL has neither the classifiers nor XXH64; the stages are tested against brute force.
ORACLE_SQL = None


def run(spark, sf_dir):
    docs, folder = table(spark, sf_dir, "documents"), f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    before = None
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            path = f"{folder}/{k}_{name}"
            docs.write.parquet(path)
            docs = spark.read.parquet(path)
            if before:  # all that was read of it has been written on
                removed(spark, before)
            before = path
    return docs
