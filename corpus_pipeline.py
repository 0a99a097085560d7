"""Corpus pipeline: documents are filtered for quality, cleared of repeats, rid of personal data and packed for training."""

from __future__ import annotations

import public_tokenizers

from fewbit.llm._store import settled, table
from fewbit.llm.line_dedup import without_repeats
from fewbit.llm.ngram_join import keep_one
from fewbit.llm.packing import pack, packed_rows
from fewbit.llm.pii import redact_pii
from fewbit.llm.quality import keep_good

#: Pieces that a packing worker remembers; fewer than alone, as executors are full of what earlier stages left in them.
CACHE = 45_000


def quality(spark, docs, sf_dir):
    """Documents that the classifier, fitted on `labels`, scores 0.7 or more.

    Null, empty and wordless texts are scored like any other (as one passage without bytes). Very long texts are read
    whole, some passages at a time. Rows that repeat an id are judged each by its own text, equal texts alike. Without
    labels of both kinds the score is the share of good ones, 0.5 if there are none. An empty table gives an empty one;
    columns named as this stage's own (score) come through unchanged.
    """
    return keep_good(docs, table(spark, sf_dir, "labels"))


def lines(spark, docs, sf_dir):
    """Later copies of repeated passages of lines, 50 words or more, are cut; documents of which nothing is left go.

    The first copy, by doc_id and then by place, stays. Null texts and rows without doc_id stay as they are, and so do
    empty texts, as nothing was cut from them. Rows that repeat a doc_id are cut alike. n_chars follows the text. An empty
    table gives an empty one; clashing columns (n_lines, n_removed, removed) come through unchanged.
    """
    return without_repeats(docs)


def near_duplicates(spark, docs, sf_dir):
    """One document, the smallest doc_id, of each group linked by five-word shingles at a Jaccard similarity of 0.8.

    Null, empty and wordless texts have no partner and stay; rows without doc_id stay. Rows that repeat a doc_id are one
    document and stay or go together. Texts of fewer than five words are compared as one shingle. Whole texts count,
    however long. An empty table gives an empty one; all columns come through unchanged.
    """
    return keep_one(docs)


def personal_data(spark, docs, sf_dir):
    """Personal data and secrets are replaced by their kind in brackets.

    No row goes. Null texts stay null, empty ones empty; repeated rows are changed alike; spans that overlap are replaced
    as one, named by the first. n_chars follows the text. An empty table gives an empty one; other columns, whatever
    their names, come through unchanged.
    """
    return redact_pii(docs)


def packing(spark, docs, sf_dir):
    """Pieces of at most 4096 tokens with their places in sequences.

    Null and empty texts are the one closing id. Rows that repeat a doc_id, or have none, are documents of their own; very
    long texts are cut in pieces. Of equal lengths any may come first. An empty table gives no sequence; other columns are
    not read.
    """
    return packed_rows(pack(docs, public_tokenizers.path("word_bpe_49k.json"), cache=CACHE))


STAGES = [
    ("quality", quality),
    ("lines", lines),
    ("near_duplicates", near_duplicates),
    ("personal_data", personal_data),
    ("packing", packing),
]

#: No stage but the fourth could be said in SQL; tests/llm holds the pipeline against a plain version.
ORACLE_SQL = None


def run(spark, sf_dir):
    docs, former = table(spark, sf_dir, "documents"), None
    for _, stage in STAGES[:-1]:
        kept = settled(lambda stage=stage, docs=docs: stage(spark, docs, sf_dir))
        if former:
            former.drop()
        docs, former = kept.df, kept
    return STAGES[-1][1](spark, docs, sf_dir)
