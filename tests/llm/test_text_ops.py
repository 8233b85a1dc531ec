import functools
import hashlib
import re
import zlib
from collections import Counter, defaultdict

import pytest

from rowproduct.llm import licenses, packing, quality, warc
from rowproduct.llm.queries import tokenizer_file
from rowproduct.llm.scratch import new_path

ODD = [
    (1, "", "en", "a"), (2, None, "en", None), (3, "one two", None, "a"), (3, "one two", None, "a"),
    (None, "CC  BY, General\tPublic-License all rights reserved", "de", "b"), (5, "word " * 3000, "en", "a"),
    (6, "lİcense ccK by K cc by", "en", "b"), (7, "a b c d e f a b c d e f x\n\n a\n a\nb\n\x0b\nb", "en", "b"),
    (8, "It's <|endoftext|>é 'll Été, ÇA. 3.14 日本 naïve… x", "fr", "c"), (9, "% # $ & | < > * word", "en", "c"),
    (10, "released under the MIT license. Licensed under the Apache License, Version 2.0", "en", "c"),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(*r, 0, 7, "x") for r in ODD], "doc_id long, text string, lang string, source string, n_chars long, n_words int, kept string")


def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def brute_quality(text):
    text = text or ""
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines = [x for x in text.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    at = defaultdict(list)
    for i in range(len(w) - 4):
        at[tuple(w[i : i + 5])].append(i)
    rep = {i + k for v in at.values() if len(v) > 1 for i in v for k in range(5)}
    failed = len(w) < 10 or 100 * len(rep) > 20 * len(w)
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(rep), failed


def test_quality_measures(spark, sf, odd):
    for df in (docs(spark, sf), odd):
        got = Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in quality.measure(df).collect())
        want = Counter((r.doc_id, *brute_quality(r.text)) for r in df.collect())
        assert got == want


def test_quality_order_never_changes_verdicts(spark, sf, odd):
    rules = quality.BASE_RULES + quality.OWN_RULES
    want = Counter((r.doc_id, r.kept) for r in quality.measure(odd).collect())
    for ordered in (list(rules), list(reversed(rules))):
        out = quality.with_verdict(odd, ordered=ordered)
        assert out.columns == ["doc_id", "text", "lang", "source", "n_chars", "n_words", "kept"]
        assert Counter((r.doc_id, r.kept) for r in out.collect()) == want
        assert {r.n_words for r in out.collect()} == {7}
    assert quality.measure(odd.limit(0)).count() == 0


def test_quality_order_by_rejections_per_cost():
    a, b, c, d = (quality.Rule(x, "true", (g,)) for x, g in (("a", "words"), ("b", "repeats"), ("c", "symbols"), ("d", "repeats")))
    costs = {"words": 1.0, "symbols": 1.0, "lines": 1.0, "repeats": 10.0, "letters": 1.0}
    rows = [(True, True, False, True)] * 2 + [(False, True, False, False)] * 7 + [(False, False, True, True)]
    # a: 2 for 1; b: 9 for 11; c: 1 for 1; d: 3 for 11. After a, b's words are paid for; after b, d costs nothing more but rejects only c's row.
    assert [r.name for r in quality.pick_order((a, b, c, d), costs, rows)] == ["a", "c", "b", "d"]
    assert [r.name for r in quality.pick_order((a, b, c, d), costs, rows, paid=("words", "repeats"))] == ["b", "d", "a", "c"]
    assert quality.pick_order((a, b), costs, []) == [a, b] and quality.pick_order((), costs, rows) == []


def test_quality_order_is_estimated_on_a_random_sample(spark):
    # The first rows are all of one kind, most others full of symbols.
    rows = [(k, "plain words of a text that nobody rejects at all here") for k in range(300)] + [(k, "$$$ %%% &&& ### some of these words are symbols only $$$$$$$$$$$$$$$$") for k in range(300, 3000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    fixed = dict.fromkeys(quality.GROUPS, 1.0)
    assert quality.order_rules(df, quality.OWN_RULES, sample_rows=100, costs=fixed)[0].name == "symbols"
    costs, _ = quality.estimate(quality.sampled(df, sample_rows=50), quality.OWN_RULES)
    assert set(costs) == {"words", "symbols", "lines", "letters"} and min(costs.values()) > 0
    assert quality.order_rules(df.limit(0), quality.OWN_RULES, costs=fixed) == list(quality.OWN_RULES)


def test_quality_skips_rules_of_rejected_rows(spark):
    """A rule that raises never runs on a row that an earlier one has rejected."""
    rows = [(1, "few words"), (2, "again " * 50), (3, "$ % & # * ten words or more are here in this text " + "$" * 90)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    loud = quality.Rule("loud", "raise_error(concat('ran on ', n_letter_words)) is null", ("words", "letters"))
    symbols = quality.OWN_RULES[0]
    assert all(not r.kept for r in quality.measure(df, own=(symbols, loud), ordered=[symbols, loud]).collect())
    assert all(not r.kept for r in quality.with_verdict(df, ordered=[*quality.BASE_RULES, symbols, loud]).collect())
    for out in (quality.measure(df, own=(symbols, loud), ordered=[loud, symbols]), quality.with_verdict(df, ordered=[*quality.BASE_RULES, loud, symbols])):
        with pytest.raises(Exception, match="ran on"):
            out.collect()


def test_quality_keeps_clean(spark, sf):
    q = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").join(spark.read.parquet("/root/testdata/sf0.01/labels.parquet"), "doc_id")
    out = quality.with_verdict(q).groupBy("quality").agg({"*": "count", "kept": "max"})
    kept = {(r.quality, r.kept): r["count"] for r in quality.with_verdict(q).groupBy("quality", "kept").count().collect()}
    assert kept.get((1, False), 0) <= 0.03 * kept[(1, True)]
    assert out.count() == 2


def test_quality_native(spark, sf):
    plan = quality.measure(docs(spark, sf))._jdf.queryExecution().toString()
    assert not re.search("Python|Arrow|Pandas", plan) and "Exchange" not in plan


def brute_license(text):
    low = re.sub("[A-Z]", lambda m: m[0].lower(), text or "")
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
    hits = [(i, p.label) for p in licenses.BASE for k in [p.words.split()] for i in range(len(w) - len(k) + 1) if w[i : i + len(k)] == k]
    starts = [i for i, _ in hits]
    return len(w), len(hits), min(starts, default=None), max(starts, default=None), ",".join(sorted({x for _, x in hits}))


def test_license_base(spark, sf, odd):
    for df in (docs(spark, sf), odd):
        got = Counter((r.doc_id, r.n_words, r.n_base, r.first_word, r.last_word, r.base_labels) for r in licenses.scan(df).collect())
        assert got == Counter((r.doc_id, *brute_license(r.text)) for r in df.collect())
    by = {r.doc_id: r for r in licenses.scan(odd).collect()}
    assert by[10].labels == "apache-2.0,mit" and by[10].score == 1.0 and by[1].score == 0.0
    assert set(by[None].base_labels.split(",")) <= set(by[None].labels.split(","))
    plan = licenses.scan(odd)._jdf.queryExecution().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


def test_license_near_copy_merges_diagonals(spark):
    notice = licenses.NOTICES[1].words.split()
    text = " ".join(notice[:8] + ["extra"] + notice[8:])  # a word put in: two neighbouring diagonals
    far = " ".join(notice[:9])  # under the cover
    rows = {r.doc_id: r.labels for r in licenses.scan(spark.createDataFrame([(1, text), (2, far)], "doc_id long, text string")).collect()}
    assert rows == {1: "mit", 2: ""}


def test_license_no_false_labels(spark):
    """What holds only a few of a notice's words, however often, is none of it."""
    notice = {p.label: p.words for p in licenses.NOTICES}
    rows = [
        (1, "cc by " * 5), (2, "the general public of the general public and general public or general public"), (3, "general public license " * 6),
        (4, notice["gpl-2.0"]), (5, notice["gpl-3.0"]), (6, notice["cc-by-sa-4.0"]),
        (7, " ".join(reversed(notice["unlicense"].split()))), (8, "public domain into the released unencumbered software free and is this " * 4),
        (9, notice["unlicense"] + " and again " + notice["unlicense"]), (10, notice["isc"].replace("modify", "alter")),
        (11, "into the public domain software released into the free and unencumbered this is free"),
    ]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: (r.labels, r.score) for r in licenses.scan(df).collect()}
    assert got[1] == ("cc-by", 1.0) and got[2] == ("", 0.0) and got[3] == ("gpl", 1.0)
    assert got[4][0] == "gpl,gpl-2.0" and got[5][0] == "gpl,gpl-3.0" and got[6][0] == "cc-by,cc-by-sa-4.0"
    assert got[7] == got[8] == got[11] == ("", 0.0) and got[9] == ("unlicense", 1.0) and got[10][0] == "isc" and 0.8 <= got[10][1] < 1
    n = len(notice["unlicense"].split())
    places = sorted((r.first_word, r.last_word) for r in licenses.spans(df).where("doc_id = 9 and label is not null").collect())
    assert places == [(0, n - 1), (n + 2, 2 * n + 1)]


@functools.lru_cache
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(tokenizer_file(packing.TOKENIZER))


def whole(text):
    return [*library().encode(text or "", add_special_tokens=False).ids, 1]


def check_pack(rows, texts, length):
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in rows:
        by_doc[r.doc_id].append(r), by_seq[r.sequence_id].append(r)
    import numpy as np

    for d, ids in texts.items():
        at = 0
        for r in sorted(by_doc[d], key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids)
            assert r.ids_crc32 == zlib.crc32(np.asarray(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    pad = 0
    for s in by_seq.values():
        at = 0
        for r in sorted(s, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= length
        pad += 0 if at & (at - 1) == 0 else length - at
    assert pad == 0 and sorted(by_seq) == list(range(len(by_seq)))


def test_packing(spark, sf, odd):
    df = docs(spark, sf)
    texts = {r.doc_id: whole(r.text) for r in df.collect()}
    check_pack(packing.pack(df, tokenizer_file(packing.TOKENIZER), window_sequences=4).collect(), texts, 2048)
    one = odd.where("doc_id is not null").dropDuplicates(["doc_id"])
    check_pack(packing.pack(one, tokenizer_file(packing.TOKENIZER), length=64, window_sequences=2).collect(), {r.doc_id: whole(r.text) for r in one.collect()}, 64)
    assert packing.pack(odd.limit(0), tokenizer_file(packing.TOKENIZER)).count() == 0
    assert sum(r.length for r in packing.pack(odd, tokenizer_file(packing.TOKENIZER)).collect()) == sum(len(whole(t)) for _, t, *_ in ODD)


def test_packing_holds_the_mixture(spark, sf):
    df = docs(spark, sf)
    rows = packing.pack(df, tokenizer_file(packing.TOKENIZER), window_sequences=4, targets={"src0": 0.5, "src1": 0.3}).collect()
    first = [r for r in rows if r.sequence_id < 4]
    n = Counter()
    for r in first:
        n[r.source] += r.length
    all_n = Counter()
    for r in rows:
        all_n[r.source] += r.length
    weights = {q: {"src0": 0.5, "src1": 0.3}.get(q, all_n[q] / sum(all_n.values())) for q in all_n}
    for q in n:  # until a queue runs dry, each window holds its share within a token a queue
        assert abs(n[q] / sum(n.values()) - weights[q] / sum(weights.values())) < 0.01


def test_word_tokenizer_equals_library(spark, sf):
    t = packing.WordTokenizer(tokenizer_file(packing.TOKENIZER))
    for _, text, *_ in ODD:
        assert [*memoryview(t.encode(text or "")).cast("H")] == whole(text)[:-1]


def test_warc(spark, sf):
    long = "x" * 1200
    rows = [(1, "http://a", long), (2, "http://b", long), (3, None, "short"), (4, "u\r\nX: y", "short"), (5, "n", None), (2, "http://b", long), (None, "z", long), (None, "z", long), (7, "é", "é" * 999 + "\r\n\r\n"),
            (8, " padded ", "WARC/1.1\r\nContent-Length: 3\r\n\r\nabc" + "\r\n" * 4 + "tail" * 400), (9, "big", "0123456789abcdef" * 200_000)]
    mine = spark.createDataFrame([(*r, "q") for r in rows], "page_id long, url string, html string, sha256 string")
    many = spark.createDataFrame([(k, "u", "same short page") for k in range(9000)], "page_id long, url string, html string")  # dealt to several tasks
    for pages in (mine, spark.read.parquet(f"{sf}/pages.parquet"), many, mine.limit(0)):
        path, out = new_path(spark, "w"), new_path(spark, "x")
        warc.write_archive(pages, path)
        data = [(r.page_id, (r.html or "").encode()) for r in pages.collect()]
        top = {}
        for i, b in data:
            top[b] = max(top.get(b, -1), -1 if i is None else i)
        want = Counter()
        for i, b in data:
            rev = i is not None and len(b) >= 1000 and i < top[b]
            want[(i, len(b), hashlib.sha1(b).hexdigest(), "revisit" if rev else "response", top[b] if rev else None)] += 1
        assert spark.read.parquet(f"{path}/payloads").count() == len({b for _, b in data})
        assert warc.read_payloads(spark, path).where("not good").count() == 0
        warc.export_warc(spark, path, out, file_bytes=50_000)
        got = Counter((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to) for r in warc.read_pages(spark, out).collect())
        assert got == want
        records = warc.read_warc(spark, out).where("record_type <> 'warcinfo'").collect()
        assert len({r.record_id for r in records}) == len(data)  # repeated rows and null ids have ids of their own
        back = Counter((r.record_type, r.payload_digest, bytes(r.payload)) for r in records)
        assert back == Counter((k, f"sha1:{hashlib.sha1(b).hexdigest()}", b"" if k == "revisit" else b) for i, b in data for k in ["revisit" if i is not None and len(b) >= 1000 and i < top[b] else "response"])


def test_warc_notices_changed_bytes(spark):
    import glob
    import gzip
    import os

    page = "<p>" + "words of a page " * 100
    pages = spark.createDataFrame([(1, "http://a", page), (2, "http://b", page), (3, "http://c", "short")], "page_id long, url string, html string")
    path, out = new_path(spark, "w"), new_path(spark, "x")
    warc.write_archive(pages, path)
    warc.export_warc(spark, path, out)
    files = [f for f in glob.glob(f"{out}/part-*")]
    assert files and warc.read_pages(spark, out).count() == 3
    good = b"".join(gzip.decompress(open(f, "rb").read()) for f in files)
    for old, new in ((b"words of a page words", b"words of a Page words"), (b"short\r\n", b"shirt\r\n"), (b"Refers-To: <urn:uuid:", b"Refers-To: <urn:uuid:0"), (b"Content-Length: ", b"Content-Length: 9")):
        assert old in good
        bad = new_path(spark, "bad")
        os.makedirs(bad)
        with open(f"{bad}/pages.warc", "wb") as f:
            f.write(good.replace(old, new, 1))
        with pytest.raises(Exception):
            warc.read_pages(spark, bad).collect()


def test_warc_of_other_writers(spark):
    import gzip
    import os

    body = b"HTTP/1.0 200 OK\nX: y\n\n<html>\xff</html>"
    sha = hashlib.sha1(body[body.index(b"\n\n") + 2 :])
    import base64

    b32 = base64.b32encode(sha.digest()).decode()
    info = b"WARC/1.0\r\nwarc-type:warcinfo\r\nWARC-Record-ID: <urn:x:1>\r\nContent-Length: 3\r\n\r\na:b\r\n\r\n"
    rec = f"WARC/1.0\r\nWARC-TYPE:  response \r\nno colon here\r\nWARC-Record-ID:<urn:x:2>\r\nX-Long: one\r\n two\r\nwarc-payload-digest: SHA1:{b32}\r\nContent-Type: application/http;msgtype=response\r\ncontent-length:{len(body)}\r\n\r\n".encode() + body + b"\r\n\r\n"
    lf = rec.replace(b"\r\n", b"\n").replace(b"urn:x:2", b"urn:x:3")
    folder = new_path(spark, "other")
    os.makedirs(folder)
    for name, data in (("a.warc", info + rec + b"\r\n"), ("b.warc.gz", gzip.compress(info) + gzip.compress(rec)), ("c", lf), ("empty.warc", b"")):
        with open(f"{folder}/{name}", "wb") as f:
            f.write(data)
    got = sorted((r.record_id, r.record_type, r.digest_holds, r.uri) for r in warc.read_warc(spark, folder).collect())
    assert got == [("urn:x:1", "warcinfo", None, None)] * 2 + [("urn:x:2", "response", True, None)] * 2 + [("urn:x:3", "response", True, None)]
    with pytest.raises(ValueError):
        list(warc.parse(rec[:-20]))
    with pytest.raises(ValueError):
        list(warc.parse(b"no archive"))
