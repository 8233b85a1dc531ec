"""Line dedup by pairwise alignment.

A line with enough words for a block is rare enough to tell who overlaps with whom; a shorter one is joined to its
neighbours until there are enough: from each line on, and up to each line, the shortest run of `min_block_words`
words is hashed. These runs cover every block without gaps that two documents can share. A run that more
than one document holds pairs each later document with its first holder, so that a run of a million documents makes
a million pairs, not a square of them, and no run is too common to count.

A pair is aligned by patience diff: runs that stand once in both documents anchor the longest chain that
rises in both, runs beside the chain on the same diagonal join it, and what the chain leaves out is aligned again, so that
moved blocks are found. An aligned block is cut from the later document. A block whose holder is not the
first holder of its runs is found through the runs' own first holders: deletions equal those of
aligning all pairs of documents.

Documents are ordered by id, equal ids by text hash. Defined results: lines are compared
without white space at their ends; lines without words belong to no block but go where both
neighbours go with one; null ids take no part and stay; null and empty texts stay; repeated rows
(equal id and text) are treated alike, neither later than the other; extra columns stay, whatever their names.
"""

from __future__ import annotations

from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator
from itertools import groupby

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .scratch import stored

MIN_BLOCK_WORDS, ROUNDS = 10, 16
RUN = "h binary, doc long, th long, lo int, hi int, first int, last int, before int, upto int, once boolean"
BLOCK = "doc long, th long, holder long, holder_th long, lo int, hi int, holder_lo int, first int, last int, before int, upto int"
_ARROW = {"binary": pa.binary(), "long": pa.int64(), "int": pa.int32(), "boolean": pa.bool_()}


def _schema(ddl: str) -> pa.Schema:
    return pa.schema([(n, _ARROW[t]) for n, t in (x.split() for x in ddl.split(", "))])


def shortest_runs(words: list[int], least: int) -> set[tuple[int, int]]:
    """(lo, hi) of the shortest runs of lines that end or begin at each line and hold `least` words."""
    runs, lo, held = set(), 0, 0
    for hi, m in enumerate(words):  # up to each line
        held += m
        while held - words[lo] >= least:
            held, lo = held - words[lo], lo + 1
        if held >= least:
            runs.add((lo, hi))
    hi, held = -1, 0
    for lo, m in enumerate(words):  # from each line on
        while held < least and hi + 1 < len(words):
            hi += 1
            held += words[hi]
        if held < least:
            break
        runs.add((lo, hi))
        held -= m
    return runs


def run_table(docs: DataFrame, least: int, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """A row for each shortest run: lo and hi count lines that hold words, first and last all lines, before and upto the
    words ahead of the run and those up to its end; once: the document has the run only there."""
    schema = _schema(RUN)

    def of(doc, th, t) -> Iterator[tuple]:
        own = [(x, p) for p, y in enumerate((t or "").encode("utf-8", "surrogatepass").split(b"\n")) if (x := y.strip())]
        n = [len(x.split()) for x, _ in own]
        upto = [0]
        for m in n:
            upto.append(upto[-1] + m)
        keys = [(xxhash.xxh3_128_digest(b"\n".join(x for x, _ in own[lo : hi + 1])), lo, hi) for lo, hi in sorted(shortest_runs(n, least))]
        times = Counter(k for k, _, _ in keys)
        for h, lo, hi in keys:
            yield h, doc, th, lo, hi, own[lo][1], own[hi][1], upto[lo], upto[hi + 1], times[h] == 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []
        for b in batches:
            for k in range(0, b.num_rows, 500):
                for row in zip(*(c.to_pylist() for c in b.slice(k, 500).columns), strict=True):
                    out += of(*row)
                    if len(out) >= 20_000:
                        yield _batch(out, schema)
                        out = []
        if out:
            yield _batch(out, schema)

    d = docs.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("th"), F.col(text).alias("text"))
    return d.mapInArrow(run, RUN)


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), schema.types, strict=True)], schema.names)


def rising(values: list[int]) -> list[int]:
    """Indexes of a longest strictly rising chain, by patience piles."""
    tops: list[int] = []
    pile: list[int] = []
    back = [-1] * len(values)
    for k, v in enumerate(values):
        p = bisect_left(tops, v)
        back[k] = pile[p - 1] if p else -1
        if p == len(tops):
            tops.append(v), pile.append(k)
        else:
            tops[p], pile[p] = v, k
    out, k = [], pile[-1] if pile else -1
    while k >= 0:
        out.append(k)
        k = back[k]
    return out[::-1]


def align(runs: list[tuple[int, int, int, bool]]) -> list[tuple[int, int, int]]:
    """runs (lo, hi, holder's lo, once in both) that one pair of documents shares -> blocks (lo, hi, holder's lo), each
    longest on its diagonal. Every run ends in a block: a chain takes what rises in both documents, and runs that
    cross it are aligned in a round of their own; after ROUNDS of them what is left crosses everywhere and is taken as it is."""
    left = sorted(set(runs), key=lambda x: (x[0], -x[2], x[1]))
    out: list[tuple[int, int, int]] = []
    aligned: set[int] = set()
    for turn in range(ROUNDS + 1):
        if not left:
            break
        pool = [x for x in left if x[3]] or left
        chain = left if turn == ROUNDS else [pool[k] for k in rising([x[2] for x in pool])]
        on = {x[2] - x[0] for x in chain}
        by: dict[int, list[list[int]]] = {}
        for lo, hi, at, _ in left:  # of those on a chain's diagonal, touching runs make one block
            if at - lo in on:
                own = by.setdefault(at - lo, [])
                if own and lo <= own[-1][1] + 1:
                    own[-1][1] = max(own[-1][1], hi)
                else:
                    own.append([lo, hi])
        for shift, blocks in by.items():
            for lo, hi in blocks:
                out.append((lo, hi, lo + shift))
                aligned.update(range(lo, hi + 1))
        left = [x for x in left if not aligned.issuperset(range(x[0], x[1] + 1))]
    return out


def aligned_blocks(docs: DataFrame, min_block_words: int = MIN_BLOCK_WORDS, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """Blocks of at least min_block_words words that a document shares with an earlier one (holder), with both places. Blocks of
    one document with different holders may overlap."""
    spans = run_table(docs, min_block_words, id_col, text)
    own = spans.groupBy("h").agg(F.min(F.struct("doc", "th", "lo", "once")).alias("e"), F.max(F.struct("doc", "th")).alias("l"))
    # Written, so that the join deals both its sides anew and a run that many documents hold can be split over tasks.
    held = stored(own.where("e.doc <> l.doc or e.th <> l.th").select("h", "e"), "first-holders")
    later = (F.col("doc") > F.col("e.doc")) | ((F.col("doc") == F.col("e.doc")) & (F.col("th") > F.col("e.th")))
    rows = spans.join(held, "h").where(later).select(
        "doc", "th", F.col("e.doc").alias("holder"), F.col("e.th").alias("holder_th"), "lo", "hi", F.col("e.lo").alias("holder_lo"), "first", "last", "before", "upto", (F.col("once") & F.col("e.once")).alias("once"))
    rows = rows.repartition("doc", "th").sortWithinPartitions("doc", "th", "holder", "holder_th", "lo", "hi")
    schema = _schema(BLOCK)

    def stream(batches: Iterator[pa.RecordBatch]):
        for b in batches:
            yield from zip(*(c.to_pylist() for c in b.columns), strict=True)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple] = []
        for pair, own in groupby(stream(batches), key=lambda r: r[:4]):
            own = list(own)  # repeated rows fall together here
            begin, end = {r[4]: (r[7], r[9]) for r in own}, {r[5]: (r[8], r[10]) for r in own}
            for lo, hi, at in align([(r[4], r[5], r[6], r[11]) for r in own]):
                out.append((*pair, lo, hi, at, begin[lo][0], end[hi][0], begin[lo][1], end[hi][1]))
            if len(out) >= 20_000:
                yield _batch(out, schema)
                out = []
        if out:
            yield _batch(out, schema)

    return rows.mapInArrow(run, BLOCK)


def dropped(docs: DataFrame, min_block_words: int = MIN_BLOCK_WORDS, id_col: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc, th, runs array<struct<first, last>>, lines, words): stretches of line places that go, for documents that lose any;
    lines counts those that hold words."""
    # A document's blocks lie in one partition already; touching and overlapping blocks make one stretch.
    b = F.array_sort(F.collect_set(F.struct("lo", "hi", "first", "last", "before", "upto")))
    per = aligned_blocks(docs, min_block_words, id_col, text).groupBy("doc", "th").agg(b.alias("b"))
    piece = lambda x, old: F.struct(
        old["lo"].alias("lo"), F.greatest(old["hi"], x["hi"]).alias("hi"), old["first"].alias("first"), F.greatest(old["last"], x["last"]).alias("last"),
        old["before"].alias("before"), F.greatest(old["upto"], x["upto"]).alias("upto"))
    merge = lambda acc, x: F.when(
        (F.size(acc) > 0) & (x["lo"] <= F.element_at(acc, -1)["hi"] + 1),
        F.concat(F.slice(acc, 1, F.size(acc) - 1), F.array(piece(x, F.element_at(acc, -1))))).otherwise(F.concat(acc, F.array(x)))
    empty = F.expr("cast(array() as array<struct<lo:int,hi:int,first:int,last:int,before:int,upto:int>>)")
    per = per.withColumn("b", F.aggregate("b", empty, merge))
    count = lambda f: F.aggregate("b", F.lit(0).cast("long"), lambda n, x: n + f(x))
    return per.select("doc", "th", F.transform("b", lambda x: F.struct(x["first"].alias("first"), x["last"].alias("last"))).alias("runs"),
                      count(lambda x: x["hi"] - x["lo"] + 1).cast("int").alias("lines"), count(lambda x: x["upto"] - x["before"]).alias("words"))


def dedup_lines(docs: DataFrame, min_block_words: int = MIN_BLOCK_WORDS, id_col: str = "doc_id", text: str = "text", counts: bool = False) -> DataFrame:
    """docs with the common blocks gone from later documents' texts; counts: also dropped_lines and dropped_words, which take
    the place of columns so named."""
    gone = dropped(docs, min_block_words, id_col, text)
    new = ("dropped_lines", "dropped_words") if counts else ()
    names = [c for c in docs.columns if c not in new]
    # The row travels as one value, so that its columns can have any name.
    keyed = docs.select(F.struct(*names).alias("row"), F.col(id_col).cast("long").alias("doc"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("th"))
    both = keyed.join(gone, ["doc", "th"], "left")
    own = F.col("row").getField(text)
    left = F.array_join(F.filter(F.split(own, "\n", -1), lambda _, i: ~F.exists("runs", lambda r: i.between(r["first"], r["last"]))), "\n")
    cut = F.when(F.col("runs").isNull(), own).otherwise(left)
    extra = [F.coalesce("lines", F.lit(0)).alias(new[0]), F.coalesce("words", F.lit(0)).cast("long").alias(new[1])] if counts else []
    return both.select(*[(cut if c == text else F.col("row").getField(c)).alias(c) for c in names], *extra)
