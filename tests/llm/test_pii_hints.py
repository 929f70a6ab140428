"""Texts that a generator's pattern matches are scanned by it."""

from curvesolve.llm import pii


def test_spaced_address_without_at_is_a_candidate(spark):
    df = spark.createDataFrame([(1, "x @ y . com"), (2, "x (at) y (dot) com"), (3, "none")], "doc_id long, text string")
    got = {r["doc_id"]: [(c["kind"], c["s"], c["e"]) for c in r["c"]] for r in pii.candidates(df).select("doc_id", "c").collect()}
    kind = pii.KINDS.index("loose_email")
    assert got == {1: [(kind, 0, 11)], 2: [(kind, 0, 18)], 3: []}
