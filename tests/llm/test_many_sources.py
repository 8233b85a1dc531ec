"""Packing keeps true sources however many there are."""

from rowproduct.llm import packing
from rowproduct.llm.queries import tokenizer_file


def test_many_sources_keep_names_and_targets(spark):
    n = 5000
    rows = [(k, "one two three four five " * 4, f"site{k}") for k in range(n)] + [(n + k, "big source words here " * 50, "big") for k in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = packing.pack(df, tokenizer_file(packing.TOKENIZER), length=256, window_sequences=4, targets={"big": 1.0, "site7": 0.5} | {f"site{k}": 1e-6 for k in range(100, n)}).collect()
    assert {r.source for r in got} == {s for *_, s in rows}
    of = {d: s for d, _, s in rows}
    assert all(r.source == of[r.doc_id] for r in got)
    first = {}
    for r in got:
        if r.sequence_id < 4:
            first[r.source] = first.get(r.source, 0) + r.length
    assert first["big"] > 500  # its target holds in the first window
    by = {}
    for r in sorted(got, key=lambda r: (r.doc_id, r.start)):
        assert r.start == by.get(r.doc_id, 0)
        by[r.doc_id] = r.start + r.length
        assert r.length and by[r.doc_id] <= r.doc_tokens
    assert all(by[r.doc_id] == r.doc_tokens for r in got)
