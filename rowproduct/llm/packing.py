"""Mixture-controlled packing of token streams into fixed windows.

Deficit round-robin over source queues, in closed form: in every window each queue earns its
target share of the window's tokens and keeps the fraction it could not spend, so after w
windows queue s has sent floor(min(total_s, share_s * time(w))) tokens, where time(w) is
the round at which all queues together have earned w windows; queues that run dry leave
their share to the rest. A token's place in the output follows from its place in its queue,
so the schedule needs only the queues' totals and no task waits for another. Windows
follow each other without gaps and are cut into sequences of `length` tokens; what is left
at the end becomes sequences of falling powers of two, which need no padding.

Defined results: null text is an empty document (one end token); null sources share one
queue, a source named like it included; every source keeps its own queue, however many there are (the
driver and each task hold a name and a total of each); repeated rows are packed as often as they occur;
an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import unicodedata
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .scratch import stored
from .words import LazyMemo

LENGTH, WINDOW_SEQUENCES, PREFIX_ROWS = 2048, 64, 500_000
#: Entries of window tables (windows times sources) that a task keeps.
KEPT_ENTRIES = 2_000_000
TOKENIZER = "word_bpe_49k.json"


def _byte_letters() -> list[str]:
    """The printable letter that byte-level vocabularies write for each byte."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    extra = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(extra)) for b in range(256)]


class WordTokenizer:
    """Ids of a tokenizer whose tokens never span white space, memoised by word.

    Words of plain Latin letters, with or without closing points and commas, go straight to
    the merge model; every other word goes through the whole tokenizer.
    """

    LETTERS = frozenset("abcdefghijklmnopqrstuvwxyzßàáâãäåæçèéêëìíîïðñòóôõöøùúûüýþÿ")

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        self.whole.no_truncation(), self.whole.no_padding()
        self.dtype = np.dtype("<u2" if self.whole.get_vocab_size() <= 65536 else "<u4")
        self.byte = _byte_letters()
        self.code, self.model = "H" if self.dtype.itemsize == 2 else "I", self.whole.model
        # Special strings may touch words, and there are separators that only Python splits at.
        self.odd = ["\x1c", "\x1d", "\x1e", "\x1f", *(t.content.lower() for t in self.whole.get_added_tokens_decoder().values())]
        self.tails: dict[str, bytes] = {}
        self.memo = LazyMemo(self._word)

    def _pack(self, ids) -> bytes:
        return np.asarray(ids, self.dtype).tobytes()

    def _whole(self, word: str) -> bytes:
        return self._pack(self.whole.encode(word, add_special_tokens=False).ids)

    def _word(self, word: str) -> bytes:
        if word.isascii() and word.isalpha():
            return array(self.code, [t.id for t in self.model.tokenize(word.lower())]).tobytes()
        stem = word.rstrip(".,")
        low = stem.lower()
        if not low or not self.LETTERS.issuperset(low):
            return self._whole(word)
        tail = word[len(stem) :]
        if tail not in self.tails:
            self.tails[tail] = self._whole(tail) if tail else b""
        low = low if low.isascii() else "".join(self.byte[b] for b in low.encode())
        return array(self.code, [t.id for t in self.model.tokenize(low)]).tobytes() + self.tails[tail]

    def encode(self, text: str) -> bytes:
        try:
            text.encode("latin-1")
            low = text.lower()  # within Latin-1, character by character and in composed form
        except UnicodeEncodeError:
            if not unicodedata.is_normalized("NFC", text):
                return self._whole(text)  # joining marks may touch spaces
            low = text
        if any(x in low for x in self.odd) or (low is text and any(x in text.lower() for x in self.odd)):
            return self._whole(text)
        return b"".join(map(self.memo.__getitem__, low.split()))


def tokenized(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text: str = "text", source: str = "source", end_id: int = 1) -> DataFrame:
    """(doc, queue, part, at, n, ids): at is the document's place among its queue's tokens
    within the task `part`; ids are its tokens' bytes, the end token last."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, part, at = WordTokenizer(tokenizer_path), TaskContext.get().partitionId(), {}
        end, size = np.asarray([end_id], tok.dtype).tobytes(), tok.dtype.itemsize
        for b in batches:
            for k in range(0, b.num_rows, 500):
                rows = b.slice(k, 500)
                queues, starts, ns, blobs = rows.column(1).to_pylist(), [], [], []
                for q, t in zip(queues, rows.column(2).to_pylist(), strict=True):
                    blob = tok.encode(t or "") + end
                    n = len(blob) // size
                    starts.append(at.get(q, 0)), ns.append(n), blobs.append(blob)
                    at[q] = at.get(q, 0) + n
                yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), pa.array([part] * len(ns), pa.int64()), pa.array(starts, pa.int64()), pa.array(ns, pa.int64()), pa.array(blobs, pa.binary()), pa.array([size] * len(ns), pa.int32())], ["doc", "queue", "part", "at", "n", "ids", "width"])

    d = docs.select(F.col(id_col).cast("long").alias("doc"), F.coalesce(F.col(source).cast("string"), F.lit("")).alias("queue"), F.col(text).alias("text"))
    return d.mapInArrow(run, "doc long, queue string, part long, at long, n long, ids binary, width int")


class Schedule:
    """Places of queue tokens in the packed stream. totals and targets by queue, in queue order."""

    def __init__(self, names, totals, targets, window: int):
        self.index = {q: k for k, q in enumerate(names)}
        self.total = np.asarray(totals, np.int64)
        share = np.asarray(targets, float)
        self.share = share / share.sum() if len(share) else share
        self.window, self.all = window, int(self.total.sum())
        self.windows = -(-self.all // window)
        # Rounds at which queues run dry, and what all have earned by then.
        dry = self.total / self.share if len(share) else np.zeros(0)
        order = np.argsort(dry, kind="stable")
        self.knots = np.concatenate([[0.0], dry[order]])
        left = np.concatenate([[1.0], 1 - np.cumsum(self.share[order])])[: len(order)]
        self.earned = np.concatenate([[0.0], np.cumsum(np.diff(self.knots) * np.maximum(left, 0))])

    def sent(self, w) -> np.ndarray:
        """Tokens that each queue has sent before window w (a vector of windows): queues x windows."""
        w = np.asarray(w, np.int64)
        time = np.interp(np.minimum(w * float(self.window), self.all), self.earned, self.knots)
        out = np.floor(np.minimum(self.total[:, None].astype(float), self.share[:, None] * time[None, :])).astype(np.int64)
        return np.where((w >= self.windows)[None, :], self.total[:, None], np.minimum(out, self.total[:, None]))

    def runs(self, queue: str, lo: int, hi: int, table: dict) -> Iterator[tuple[int, int, int]]:
        """(queue place, stream place, length) of the queue's tokens lo to hi, a run for each window they meet."""
        q = self.index[queue]
        a, b = 0, self.windows - 1  # the last window that begins at lo or before
        while a < b:
            m = (a + b + 1) // 2
            a, b = (m, b) if self._begin(q, m) <= lo else (a, m - 1)
        while lo < hi:
            begin, base, until = self._window(a, table)
            n = min(hi, int(until[q])) - lo
            if n > 0:
                yield lo, int(base[q]) + lo - int(begin[q]), n
                lo += n
            a += 1

    def _begin(self, q: int, w: int) -> int:
        """sent of one queue before one window."""
        if w >= self.windows:
            return int(self.total[q])
        time = np.interp(min(w * float(self.window), self.all), self.earned, self.knots)
        return min(int(np.floor(min(float(self.total[q]), self.share[q] * time))), int(self.total[q]))

    def _window(self, w: int, table: dict):
        if w not in table:
            if len(table) > min(2000, KEPT_ENTRIES // len(self.total)):
                table.clear()
            x = self.sent([w, w + 1])
            grants = x[:, 1] - x[:, 0]
            table[w] = x[:, 0], x[:, 0].sum() + np.cumsum(grants) - grants, x[:, 1]
        return table[w]

    def sequence(self, place: int, length: int) -> tuple[int, int, int]:
        """(sequence, offset, room) of a place in the stream."""
        full, rest = divmod(self.all, length)
        s, off = divmod(place, length)
        if s < full:
            return s, off, length - off
        part, s = 1 << (rest.bit_length() - 1), full
        while off >= part:
            off, rest, s = off - part, rest - part, s + 1
            part = 1 << (rest.bit_length() - 1)
        return s, off, part - off


def pack(docs: DataFrame, tokenizer_path: str, length: int = LENGTH, window_sequences: int = WINDOW_SEQUENCES, targets: dict[str, float] | None = None,
         id_col: str = "doc_id", text: str = "text", source: str = "source", end_id: int = 1, keep_ids: bool = False) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, source
    (and ids, with keep_ids). targets: tokens wanted by source, as weights; unnamed sources share
    what they have; None keeps the corpus' own proportions in every window.
    """
    spark = docs.sparkSession
    if source not in docs.columns:
        docs = docs.withColumn(source, F.lit(""))
    tok = stored(tokenized(docs, tokenizer_path, id_col, text, source, end_id), "tokens")
    parts = stored(tok.groupBy("queue", "part").agg(F.sum("n").alias("n")), "parts")
    totals = sorted((r[0], r[1]) for r in parts.groupBy("queue").agg(F.sum("n")).collect())  # a row a source
    names, counts = [q for q, _ in totals], [n for _, n in totals]
    weights = [n if targets is None else targets.get(q, n / max(1, sum(counts))) for q, n in totals]
    schedule = Schedule(names, counts, weights, length * window_sequences)
    before = parts.select("queue", "part", (F.sum("n").over(W.partitionBy("queue").orderBy("part")) - F.col("n")).alias("before"))
    small = parts.count() <= PREFIX_ROWS  # tasks x queues: checked, since it grows with the input
    placed = tok.join(F.broadcast(before) if small else before, ["queue", "part"])

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table: dict = {}
        for b in batches:
            for k in range(0, b.num_rows, 1000):
                r = b.slice(k, 1000).to_pydict()
                out: list[tuple] = []
                for doc, queue, lo, n, ids, width in zip(r["doc"], r["queue"], r["lo"], r["n"], r["ids"], r["width"], strict=True):
                    words = np.frombuffer(ids, f"<u{width}").astype("<u4")
                    for at, place, size in schedule.runs(queue, lo, lo + n, table):
                        at -= lo
                        while size:
                            seq, off, room = schedule.sequence(place, length)
                            m = min(size, room)
                            piece = words[at : at + m].tobytes()
                            out.append((doc, at, m, zlib.crc32(piece), n, seq, off, queue, piece if keep_ids else None))
                            at, place, size = at + m, place + m, size - m
                if out:
                    cols = list(zip(*out, strict=True))
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, [pa.int64()] * 7 + [pa.string(), pa.binary()], strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "source", "ids"])

    pieces = placed.select("doc", "queue", (F.col("before") + F.col("at")).alias("lo"), "n", "ids", "width").mapInArrow(
        cut, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, source string, ids binary")
    return pieces if keep_ids else pieces.drop("ids")
