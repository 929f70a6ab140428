"""Line deduplication of a corpus: hot single lines, and passages within long lines."""

import re

import brute as B
import numpy as np

from curvesolve.llm import line_dedup


def by_sentences(rows):
    """Sentences as lines for the plain version; a mark keeps where lines end."""
    cut = [re.sub(r"(?<=[.!?]) ", "\n", t) for _, t in rows]
    return B.line_repeats(cut, 3, 5)


def test_hot_line_goes_wherever_it_stands(spark):
    hot = "all rights reserved by the owner of this page"
    rows = [(i, f"first {i} here\n{hot}\nlast {i}") for i in range(6)]
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_corpus(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {i: t if i == 0 else f"first {i} here\nlast {i}" for i, t in rows}


def test_passage_within_a_line_goes_and_the_rest_keeps_its_breaks(spark):
    passage = "This sentence was seen before now. And so was the one after it!"
    rows = [(1, f"Start of one. {passage} End."), (2, f"Start of two. {passage}\nNext line. {passage}  Two blanks?  Yes.\n\n"), (3, passage), (4, None), (5, "a. b. c\nd")]
    got = {r["doc_id"]: (r["text"], r["n_gone"]) for r in line_dedup.dedup_corpus(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: (rows[0][1], 0), 2: ("Start of two.\nNext line.  Two blanks?  Yes.\n\n", 4), 3: ("", 2), 4: (None, 0), 5: (rows[4][1], 0)}


def test_random_sentences_equal_brute_force(spark):
    rng = np.random.default_rng(2)
    said = [" ".join(f"s{x}w{k}" for k in range(x + 1)) + "." for x in range(9)]
    rows = [(i, "".join(said[x] + (" " if e else "\n") for x, e in zip(rng.integers(0, 9, m), rng.integers(0, 2, m)))) for i, m in enumerate(rng.integers(0, 9, 60))]
    got = {r["doc_id"]: r["text"] for r in line_dedup.dedup_corpus(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [re.sub(r"(?<=[.!?]) ", "\n", got[i]) for i, _ in rows] == by_sentences(rows)
