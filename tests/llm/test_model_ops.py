import re
import zlib
from collections import defaultdict

import numpy as np
import pytest
import xxhash
from test_line_blocks import shared_runs

from rowproduct.llm import ann, lines, pieces, simhash, toxicity
from rowproduct.llm.components import connected_components
from rowproduct.llm.queries import PIECES, tokenizer_file

TEXTS = ["", None, "  a  b\n\nc ﬁ", "Hello world, hello", "日本語のテキスト ▁ mark", "x" * 300 + " " + "ab" * 100, " ", "\u0000 é́ 😀 tail  ", "the the the", "aaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaaa"]


@pytest.fixture(scope="module")
def model():
    from sentencepiece import SentencePieceProcessor

    return SentencePieceProcessor(model_file=tokenizer_file(PIECES))


@pytest.fixture(scope="module")
def unigram(tmp_path_factory):
    """The same vocabulary as a unigram model: the type switched, and the scores of runs of spaces, which lie so
    low that the library's 32-bit sums lose all others beside them, set below the rest."""
    import struct

    from sentencepiece import SentencePieceProcessor

    with open(tokenizer_file(PIECES), "rb") as f:
        data = bytearray(f.read())
    for n, _, a, b in pieces.fields(bytes(data)):
        for m, _, x, y in pieces.fields(bytes(data[a:b])) if n in (1, 2) else ():
            if n == 2 and m == 3:
                data[a + x] = 1
            if n == 1 and m == 2 and struct.unpack("<f", data[a + x : a + y])[0] < -1e8:
                data[a + x : a + y] = struct.pack("<f", -40000.0)
    path = tmp_path_factory.mktemp("model") / "unigram.model"
    path.write_bytes(data)
    return SentencePieceProcessor(model_file=str(path)), str(path)


@pytest.fixture(scope="module")
def some(spark, sf):
    mine = spark.createDataFrame([(10_000 + k, t, "en", "s", 1) for k, t in enumerate(TEXTS)], "doc_id long, text string, lang string, source string, n_chars long")
    return spark.read.parquet(f"{sf}/documents.parquet").limit(60).unionByName(mine).unionByName(mine.limit(2))


def test_encode_equals_library(spark, some, model):
    out = pieces.decode(pieces.encode(some, tokenizer_file(PIECES)), tokenizer_file(PIECES)).collect()
    assert len(out) == 72
    for r in out:
        want = model.encode(r.text or "")
        assert r.ids == want and r.n_tokens == len(want) and r.ids_crc32 == zlib.crc32(np.array(want, "<u4").tobytes())
        assert r.decoded == model.decode(want)
    assert pieces.encode(some.limit(0), tokenizer_file(PIECES)).count() == 0


def test_unigram_equals_library(spark, some, unigram):
    model, path = unigram
    enc = pieces.Encoder(path)
    texts = [r.text or "" for r in some.collect()]
    short = [t[:600] for t in texts]  # the library's 32-bit sums are exact there
    for t, ids in zip(short, enc.encode(short), strict=True):
        assert ids.tolist() == model.encode(t), t[:50]
    c = pieces.Counter(path)
    for t in short:
        assert sum(c.count(u)[0] for u in c.v.units(t)) == len(model.encode(t))
    counts = {(r.doc_id, r.n_tokens) for r in pieces.token_counts(some, path).collect()}
    assert counts == {(r.doc_id, sum(c.count(u)[0] for u in c.v.units(r.text or ""))) for r in some.collect()}


def test_suffix_order():
    rng = np.random.default_rng(1)
    codes = rng.integers(0, 3, 300)
    order = pieces.suffixes(codes, 16)
    cut = [tuple(codes[i : i + 16]) for i in order]
    assert cut == sorted(cut) and sorted(order) == list(range(300))


def brute_print(text, k):
    w = re.findall(rb"[^\x20\x09-\x0D]+", re.sub(rb"[A-Z]", lambda m: m[0].lower(), (text or "").encode()))
    sh = [b" ".join(w[i : i + k]) for i in range(len(w) - k + 1)] if len(w) >= k else [b" ".join(w)] if w else []
    h = [xxhash.xxh64_intdigest(s, 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def brute_components(prints, bits):
    root = {i: i for i in range(len(prints))}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(prints)):
        for j in range(i):
            if (prints[i][1] ^ prints[j][1]).bit_count() <= bits:
                root[max(find(i), find(j))] = min(find(i), find(j))
    least = defaultdict(list)
    for i in range(len(prints)):
        least[find(i)].append(prints[i][0])
    return [(d, f"{f:016x}", min(least[find(i)])) for i, (d, f) in enumerate(prints)]


def test_simhash_equals_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    extra = [(900, None), (901, ""), (902, "one"), (903, "One"), (904, "a b c d"), (904, "a b c d")]
    more = docs.unionByName(spark.createDataFrame([(i, t, "en", "z", 0) for i, t in extra], docs.schema))
    want = sorted(brute_components([(r.doc_id, brute_print(r.text, 3)) for r in more.collect()], 3))
    for leaf, block in ((8192, 16384), (16, 8)):
        got = sorted((r.doc_id, r.fingerprint, r.component_id) for r in simhash.near_duplicates(more, leaf=leaf, block=block).collect())
        assert got == want
    assert simhash.near_duplicates(docs.limit(0)).count() == 0


def test_vantage_trees_lose_no_pair():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 63, (600, 1), dtype=np.uint64)
    near = base.repeat(5, axis=0) ^ np.bitwise_or.reduce(np.uint64(1) << rng.integers(0, 64, (3000, 3)).astype(np.uint64), axis=1, keepdims=True)
    points = np.concatenate([base, near])
    lab = simhash.groups_within(points, None, 3, leaf=32)
    tree = simhash.grow(points[::3], 3, 3.0, leaf=200)
    rows, leaves = simhash.route(tree, points, 3)
    held = defaultdict(set)
    for r, leaf in zip(rows, leaves):
        held[r].add(leaf)
    for i in range(0, len(points), 7):
        for j in np.nonzero(simhash.distance(points[i][None], points) <= 3)[0]:
            assert lab[i] == lab[j] and held[i] & held[j]
    assert len(set(leaves)) > 3


def test_keep_one(spark):
    long = " ".join(f"w{k}" for k in range(400))
    rows = [(5, long), (3, long + " x"), (3, long + " x"), (9, "quite another text with its own words here"), (None, "no id at all but words"), (None, "no id at all but words")]
    docs = spark.createDataFrame([(*r, "q", 1, 2, "r") for r in rows], "doc_id long, text string, fingerprint string, _id int, _th int, row string")
    groups = simhash.near_duplicates(docs, 5, 25, (42, 43), ratio=0.8)
    assert sorted((r.doc_id or 0) for r in simhash.keep_one(docs, groups).collect()) == [0, 3, 9]
    assert simhash.keep_one(docs, groups).columns == docs.columns and {(r._id, r.row) for r in simhash.keep_one(docs, groups).collect()} == {(1, "r")}


def test_components(spark):
    rng = np.random.default_rng(2)
    e = rng.integers(0, 400, (300, 2)).tolist() + [[k, k + 1] for k in range(1000, 1040)] + [[2000, k] for k in range(2001, 2100)]
    got = {r.node: r.root for r in connected_components(spark.createDataFrame(e, "a long, b long")).collect()}
    lab = simhash.contract(2200, *np.array(e).T)
    assert got == {int(i): int(lab[i]) for p in e if p[0] != p[1] for i in p}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_toxicity_held_out(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    model = toxicity.train(docs, labels)
    rows = toxicity.score(docs, model).join(labels, "doc_id").where(toxicity.held_out("doc_id")).collect()
    hit = sum(r.predicted == 1 and r.toxic == 1 for r in rows)
    assert hit >= 0.8 * sum(r.toxic for r in rows) and sum(r.predicted == 1 and r.toxic == 0 for r in rows) <= 0.01 * len(rows)
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in rows)
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "é" * 50_000)], "doc_id long, text string")
    assert toxicity.score(odd, model).count() == 3 and toxicity.score(odd, model, keep=True).columns == ["doc_id", "text"]
    none = toxicity.train(docs, labels.limit(0))
    assert {r.score for r in toxicity.score(odd, none).collect()} == {none.score([set()])[0]}


def test_machine_learns_pairs():
    """Two terms that are harmless alone: only their product tells."""
    rng = np.random.default_rng(4)
    sets = [{*(t for t in (1, 2) if rng.random() < 0.5), *(10 + rng.integers(0, 5, 2)).tolist()} for _ in range(2000)]
    y = np.array([1 if {1, 2} <= s else 0 for s in sets])
    m = toxicity.fit(sets, y)
    linear = toxicity.Machine(np.array(sorted(m.place)), 0.0)
    assert ((m.score(sets) >= 0.7) == y).mean() > 0.99 and np.abs(m.v[:-1]).max() > 0.2 and linear.w.max() == 0


def test_line_dedup(spark, sf):
    real = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    p1, p2 = "\n".join(f"passage line {k} with seven words here" for k in range(6)), "\n".join(f"second {k} block of words again" for k in range(6))
    mine = [(1000, f"{p1}\nown a\n\n{p2}"), (1001, f"intro\n{p1}\nouttro"), (1002, f"{p2}\nmiddle of it\n{p1}"), (1003, "own a\nfree"), (1004, None), (1005, "")]
    docs = spark.createDataFrame([(*r, "x") for r in real + mine], "doc_id long, text string, _x string")
    out = {r.doc_id: r for r in lines.dedup_lines(docs, counts=True).collect()}
    want = shared_runs(real + mine, lines.MIN_BLOCK_WORDS)
    assert out[1001].text == "intro\nouttro" and out[1002].text == "middle of it" and out[1003].text == "own a\nfree" and out[1000].dropped_lines == 0
    assert out[1004].text is None and out[1005].text == "" and len(out) == len(real + mine)
    for d, t in real:
        assert out[d].text == (t if not want[d] else "\n".join(x for k, x in enumerate(t.split("\n")) if k not in want[d])), d
    assert lines.dedup_lines(docs.limit(0)).count() == 0
    twice = spark.createDataFrame([(1, p1), (1, p1), (None, p1), (2, p1)], "doc_id long, text string")
    assert sorted((r.doc_id or 0, len(r.text)) for r in lines.dedup_lines(twice).collect()) == [(0, len(p1)), (1, len(p1)), (1, len(p1)), (2, 0)]


def exact_neighbours(ids, x, every, want):
    x = x / np.linalg.norm(x, axis=1, keepdims=True)
    out = {}
    for k in np.nonzero(ids % every == 0)[0]:
        s = x @ x[k]
        order = [i for i in np.lexsort((ids, -s)) if ids[i] != ids[k]][:want]
        out[int(ids[k])] = [(int(ids[i]), float(s[i])) for i in order]
    return out


def test_nearest_neighbours(spark):
    df = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet").select("vec_id", "embedding")
    rows = [(r.vec_id, r.embedding) for r in df.collect()]
    same = [(5000 + k, rows[7][1]) for k in range(300)]  # one common vector
    bad = [(6001, None), (6002, []), (6003, [0.0] * 64), (6004, [float("nan")] * 64), (6005, [None] * 64), (6006, [1.0, 2.0]), (None, rows[0][1]), (5000, rows[7][1])]
    data = spark.createDataFrame([(*r, 1) for r in rows + same + bad], "vec_id long, embedding array<float>, node int")
    want = exact_neighbours(np.array([r[0] for r in rows + same]), np.array([r[1] for r in rows + same], float), 50, 5)
    got = defaultdict(list)
    for r in ann.neighbours(data).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.vec_id, r.score))
    assert set(got) == set(want) and all(len(v) == 5 for v in got.values())
    recall = np.mean([len({i for i, _ in got[q]} & {i for i, _ in want[q]}) / 5 for q in want])
    assert recall >= 0.95, recall
    for q, v in got.items():
        assert v == sorted(v, key=lambda p: (-p[1], p[0])) and all(i != q for i, _ in v)
    assert [i for i, _ in got[5000]] == [i for i, _ in want[5000]]
    few = data.where("vec_id < 4")
    assert {(r.query_id, r.rank) for r in ann.neighbours(few).collect()} == {(0, 1), (0, 2), (0, 3)}
    assert ann.neighbours(data.limit(0)).count() == 0


def test_nearest_neighbours_recall_at_size(spark):
    """20000 vectors without any cluster: far more than a walk sees."""
    rng = np.random.default_rng(9)
    x = rng.normal(size=(20_000, 64)).astype(np.float32)
    rows = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "vec_id long, embedding array<float>")
    want = exact_neighbours(np.arange(len(x)), x.astype(float), 200, 5)
    got = defaultdict(set)
    for r in ann.neighbours(rows, every=200).collect():
        got[r.query_id].add(r.vec_id)
    recall = np.mean([len(got[q] & {i for i, _ in want[q]}) / 5 for q in want])
    assert recall >= 0.9, recall
