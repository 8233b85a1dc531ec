"""Near-copy groups of the pipeline against a brute force over whole shingle sets."""

import random

import corpus_pipeline as cp
from rowproduct.llm import nearsets, simhash

COLS = "doc_id long, text string, lang string, source string, n_chars long"


def brute(rows):
    def of(t):
        w = (t or "").lower().split()
        return frozenset([tuple(w)] if 0 < len(w) < 5 else (tuple(w[i : i + 5]) for i in range(len(w) - 4)))

    sets, root = {i: of(t) for i, t in rows}, {i: i for i, _ in rows}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in sorted(sets):
        for j in (k for k in sorted(sets) if k < i):
            x, y = sets[i], sets[j]
            if x == y or 5 * len(x & y) >= 4 * len(x | y):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return {i: find(i) for i in sets}


def test_groups_by_whole_sets(spark):
    rng = random.Random(5)
    word = lambda: f"w{rng.randrange(3000)}"
    texts = []
    for size in (6, 8, 9, 12, 40, 150, 400):
        for _ in range(4):
            base = [word() for _ in range(size)]
            texts.append(" ".join(base))
            for edits in (1, 1, 2, 3, 5, 8, size // 20, size // 10):
                w = list(base)
                for _ in range(min(edits, size)):
                    w[rng.randrange(size)] = word()
                texts.append(" ".join(w))
    texts += [" ".join(base[k : k + 300]) for k in range(0, 101, 10)]  # a chain whose ends are apart
    texts += ["", None, "  ", "one two", "One two", "one two three", *["same words in every text here"] * 3]
    texts += [f"a line that all of these hold as one {k} {k + 1}" for k in range(40)]
    rows = list(enumerate(texts))
    rng.shuffle(rows)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute(rows)
    got = {r.doc_id: r.component_id for r in nearsets.near_groups(docs, 0.8).collect()}
    assert got == want and len(set(want.values())) < len(want)
    bits = {r.doc_id: r.component_id for r in simhash.near_duplicates(docs, cp.SHINGLE, cp.BITS, cp.SEEDS, ratio=cp.SIMILARITY).collect()}
    assert bits != want  # what the stage did before: bits alone link pairs below 0.8 and lose some above
    stage = cp.near_copies_out(spark, spark.createDataFrame([(i, t, "en", "s", 0) for i, t in rows], COLS), None)
    assert {r.doc_id for r in stage.collect()} == set(want.values())


def test_whole_sets_travel_for_pairs_that_sketches_allow(spark, monkeypatch):
    """Long texts that share most shingles, and are no near copies, meet by these; 256 parities tell none of them apart."""
    rng = random.Random(9)
    words = [f"w{k}" for k in range(2500)]
    common = " ".join(words[:1700])
    rows = [(k, common + " " + " ".join(rng.choice(words) for _ in range(700))) for k in range(12)]
    rows += [(20, rows[0][1] + " one more")]
    seen, whole = [], nearsets.verified

    def counted(pairs, sets, ratio):
        seen.append(pairs.count())
        return whole(pairs, sets, ratio)

    monkeypatch.setattr(nearsets, "verified", counted)
    got = {r.doc_id: r.component_id for r in nearsets.near_groups(spark.createDataFrame(rows, "doc_id long, text string"), 0.8).collect()}
    assert got == {k: 0 if k == 20 else k for k, _ in rows} and sum(seen) <= 2


def test_sketches_never_differ_in_more_bits_than_sets_in_elements():
    import numpy as np

    rng = np.random.default_rng(3)
    for n, m, both in ((0, 5, 0), (1, 1, 1), (40, 3000, 40), (500, 520, 400), (9000, 9100, 8000), (200_000, 1000, 900)):
        x = np.sort(rng.integers(0, 2**64, n, dtype=np.uint64))
        y = np.sort(np.concatenate([x[:both], rng.integers(0, 2**64, m - both, dtype=np.uint64)]))
        assert nearsets.odd_places(nearsets.sketch(x), nearsets.sketch(y)) <= n + m - 2 * both
