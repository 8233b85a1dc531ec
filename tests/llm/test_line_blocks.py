"""Line dedup against an independent brute force: all runs of equal lines of all pairs of documents."""

import random

from rowproduct.llm import lines

WHITE = " \t\n\x0b\x0c\r"


def shared_runs(docs, least):
    """docs: (id, text) with distinct ids -> lines (by place among all) of every longest run of equal lines, of enough words, that
    any earlier document has anywhere. Lines without words count for nothing."""
    own = {d: [(x.strip(WHITE), p) for p, x in enumerate((t or "").split("\n")) if x.strip(WHITE)] for d, t in docs}
    at = {}
    for d, rows in own.items():
        for k, (x, _) in enumerate(rows):
            at.setdefault(x, []).append((d, k))
    out = {}
    for d, rows in own.items():
        gone = out[d] = set()
        for k, (x, _) in enumerate(rows):
            for e, j in at[x]:
                if e >= d or (k and j and rows[k - 1][0] == own[e][j - 1][0]):
                    continue
                n = 0
                while k + n < len(rows) and j + n < len(own[e]) and rows[k + n][0] == own[e][j + n][0]:
                    n += 1
                if sum(len(rows[k + i][0].split()) for i in range(n)) >= least:
                    gone.update(range(k, k + n))
    return {d: {own[d][k][1] for k in v} | {p for k in v if k + 1 in v for p in range(own[d][k][1], own[d][k + 1][1])} for d, v in out.items()}


def test_every_common_block_goes_and_nothing_else(spark):
    rng = random.Random(3)
    p = " ".join(f"word{k}" for k in range(60))
    q, r, s = (" ".join(f"{c}{k}" for k in range(6)) for c in "qrs")
    docs = {
        1: ["Home", p, "x", p], 2: [p, "y", "Home"],  # a one-word line crosses the passage
        11: [q, "own of eleven"], 12: ["head of twelve", q, r], 13: [q, r, "own of thirteen"],  # 13 shares a block with 12, not with the first holder
        21: [s, "between these", s, "tail line is here"], 22: [s, "tail line is here", "own"],  # the block is at the second place
        31: ["Home", "y31", "About", p + " z"], 32: [p + " z", "Home", "x", "About"],
        41: ["a1 a2 a3 a4 a5 a6", "kept by 41"], 42: ["b1 b2 b3 b4 b5 b6", "kept by 42"], 43: ["c1 c2 c3 c4 c5 c6", "kept by 43"],
        44: ["a1 a2 a3 a4 a5 a6", "b1 b2 b3 b4 b5 b6", "c1 c2 c3 c4 c5 c6"], 45: ["new", "a1 a2 a3 a4 a5 a6", "b1 b2 b3 b4 b5 b6", "", "c1 c2 c3 c4 c5 c6"],
        51: ["l1 l2 l3 l4 l5 l6", "of 51 only", "m1 m2 m3 m4 m5 m6"], 52: ["a common line"], 53: ["l1 l2 l3 l4 l5 l6", "a common line", "m1 m2 m3 m4 m5 m6"],  # no block: the middle differs
    }
    pool = [" ".join(f"l{k}w{j}" for j in range(n)) for k, n in enumerate([1, 2, 3, 4, 5, 6, 7, 11] * 3)]
    for d in range(100, 160):
        docs[d] = [rng.choice(pool) if rng.random() < 0.9 else f"only {d} {k}" for k in range(rng.randrange(1, 14))]
        if d % 3 == 0:
            docs[d] += docs[rng.randrange(100, d)][:6] if d > 100 else []
    rows = [(d, "\n".join(x)) for d, x in docs.items()]
    want = shared_runs(rows, 10)
    got = {x.doc: {a for y in x.runs for a in range(y.first, y.last + 1)} for x in lines.dropped(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {d: v for d, v in want.items() if v} == got
    assert got[2] == {0} and got[13] == {0, 1} and got[22] == {0, 1} and got[32] == {0} and got[45] == {1, 2, 3, 4} and 44 not in got and 53 not in got


def test_blocks_name_their_holder(spark):
    p = [f"passage line {k} with seven words here" for k in range(4)]
    docs = spark.createDataFrame([(1, "\n".join(["own"] + p)), (2, "\n".join(p[2:] + ["mid"] + p[:2]))], "doc_id long, text string")
    got = sorted((b.doc, b.holder, b.lo, b.hi, b.holder_lo) for b in lines.aligned_blocks(docs).collect())
    assert got == [(2, 1, 0, 1, 3), (2, 1, 3, 4, 1)]  # moved blocks, each at its place


def test_alignment_prefers_rising_chains_and_tries_every_run():
    runs = [(0, 0, 4, True), (1, 1, 0, True), (2, 2, 1, True), (3, 3, 2, True)]
    assert lines.align(runs) == [(1, 3, 0), (0, 0, 4)]
    crossed = [(k, k, 100 - k, True) for k in range(100)]
    assert {x[0] for x in lines.align(crossed)} == set(range(100))


def test_many_holders_and_long_texts(spark):
    """One passage in a third of all documents, and a text of many lines."""
    p = "\n".join(f"shared line {k} of seven words here" for k in range(3))
    rows = [(k, f"head{k}\n{p}\ntail{k}" if k % 3 == 0 else f"alone {k}") for k in range(900)]
    long = "\n".join(f"line {k} of a very long text with ten words here" for k in range(30_000))
    rows += [(5000, long), (5001, "first of its own\n" + long)]
    out = {r.doc_id: r for r in lines.dedup_lines(spark.createDataFrame(rows, "doc_id long, text string"), counts=True).collect()}
    assert all(out[k].text == (f"head{k}\ntail{k}" if k % 3 == 0 and k else dict(rows)[k]) for k in range(900))
    assert out[5000].dropped_lines == 0 and out[5001].text == "first of its own" and out[5001].dropped_lines == 30_000


def test_clashing_names(spark):
    names = ["doc", "th", "row", "runs", "lines", "words", "_th", "_doc", "h", "dropped_lines"]
    p = "one two three four five six seven eight nine ten"
    docs = spark.createDataFrame([(1, p, *range(10)), (2, p + "\nown", *range(10))], "doc_id long, text string, " + ", ".join(f"{n} int" for n in names))
    out = lines.dedup_lines(docs)
    assert out.columns == docs.columns
    assert sorted((tuple(r) for r in out.collect())) == [(1, p, *range(10)), (2, "own", *range(10))]
    counted = lines.dedup_lines(docs, counts=True)
    assert counted.where("doc_id = 2").first().dropped_lines == 1 and len(counted.columns) == len(docs.columns) + 1
