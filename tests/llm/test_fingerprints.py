"""Fingerprints as candidates of the pipeline's near-duplicates."""

import numpy as np

from veilwalk.llm import simhash


def test_alike_documents_meet_by_their_fingerprints(spark, monkeypatch):
    """Without any bands of minima copies with a word changed meet by fingerprints alone; what the exact similarity refuses stays apart."""
    rng = np.random.default_rng(3)
    text = [f"w{x}" for x in rng.integers(0, 10**9, 3000)]
    near = [*text[:1500], "changed", *text[1501:]]
    line = " ".join(["one very common line of a notice"] * 400)
    rows = [(5, " ".join(text)), (6, " ".join(near)), (7, line + " a b c d e f g h i j k"), (8, line + " l m n o p q r s t u v"), (9, "x y z")]
    assert bin(simhash.fingerprint(rows[2][1].encode()) ^ simhash.fingerprint(rows[3][1].encode())).count("1") <= simhash.MAX_BITS
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(simhash, "_wide_links", lambda *_: [])
    monkeypatch.setattr(simhash, "FAR", -1)
    assert {r["doc_id"]: r["component_id"] for r in simhash.alike(docs).collect()} == {5: 5, 6: 5, 7: 7, 8: 8, 9: 9}
