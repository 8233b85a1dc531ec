"""The corpus pipeline against a plain Python version of all its stages."""

import re
from collections import Counter, defaultdict

from test_line_blocks import shared_runs
from test_near_sets import brute as near_sets
from test_text_ops import brute_quality, check_pack, whole

import corpus_pipeline as cp
from rowproduct.llm import quality, toxicity
from rowproduct.llm.words import WordMemo

COLS = "doc_id long, text string, lang string, source string, n_chars long"
PASSAGE = " ".join(f"shared{k} passage{k}" for k in range(40))


def plant(spark, sf):
    docs = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    clean = lambda seed, n=60: " ".join(f"{seed}word{k}" for k in range(n))
    own = {
        5000: f"{clean('a')}\n{PASSAGE}\n{clean('b')}", 5001: f"{clean('c')}\n{PASSAGE}\n{clean('d')}",
        5002: clean("exact", 120), 5003: clean("exact", 120),
        5004: clean("near", 300), 5005: clean("near", 300).replace("nearword150", "other"),
        5006: clean("tox") + " idiot moron scum stupid pathetic worthless loser", 5007: "few words", 5008: "again " * 400,
        5009: clean("alone", 200),
    }
    return docs + [(i, t, "en", "planted", len(t)) for i, t in own.items()]


def test_stages_and_run(spark, sf):
    rows = plant(spark, sf)
    docs = spark.createDataFrame(rows, COLS)
    path = spark.sparkContext.getCheckpointDir() or cp.stored(docs.limit(1), "dir") and spark.sparkContext.getCheckpointDir()
    folder = f"{path}/planted"
    docs.write.mode("overwrite").parquet(f"{folder}/documents.parquet")
    spark.read.parquet("/root/testdata/sf0.01/labels.parquet").write.mode("overwrite").parquet(f"{folder}/labels.parquet")

    model = toxicity.train(docs, spark.read.parquet(f"{folder}/labels.parquet"))
    memo = WordMemo(lambda ws: [toxicity.word_terms(w) for w in ws])
    keep = [r for r in rows if model.score([toxicity.text_terms(r[1] or "", memo)])[0] < 0.7]

    def fine(t):
        n, chars, symbols, dup, _, failed = brute_quality(t)
        lines = [x for x in t.split("\n") if x.strip(" \t\n\x0b\x0c\r")]
        return not (failed or 10 * symbols > chars or 10 * dup > 3 * len(lines) or chars > 25 * n or chars < 2 * n or 2 * len([x for x in re.findall(r"[^\x20\x09-\x0D]+", t) if re.search(r"[A-Za-z]|[^\x00-\x7f]", x)]) < n)

    keep = [r for r in keep if fine(r[1] or "")]
    gone = shared_runs([r[:2] for r in keep], 10)
    keep = [(r[0], "\n".join(x for k, x in enumerate(r[1].split("\n")) if k not in gone[r[0]]), *r[2:4]) for r in keep]
    group = near_sets([r[:2] for r in keep])
    final = {r[0]: r for r in keep if group[r[0]] == r[0]}

    got = cp.run(spark, folder).collect()
    texts = {i: whole(r[1]) for i, r in final.items()}
    assert {r.doc_id for r in got} == set(texts)
    check_pack(got, texts, 2048)
    assert {5000, 5001, 5002, 5004, 5009} <= set(texts) and not {5007, 5008} & set(texts)  # so few labels teach no sure toxicity; held-out accuracy is tested by itself
    assert PASSAGE in final[5000][1] and PASSAGE not in final[5001][1]
    assert not ({5003, 5005} & set(texts)) or all(not final[i][1] for i in {5003, 5005} & set(texts))
    assert Counter(type(s[1]).__name__ for s in cp.STAGES) == {"function": 5}


def test_stage_columns_and_empty(spark, sf):
    empty = spark.createDataFrame([], COLS)
    for name, stage in cp.STAGES[:-1]:
        out = stage(spark, empty, sf)
        assert out.columns == list(cp.COLUMNS) and out.count() == 0, name
    assert cp.STAGES[-1][1](spark, empty, sf).count() == 0
    odd = spark.createDataFrame([(None, None, None, None, None), (1, "", "en", "s", 0), (1, "", "en", "s", 0), (2, "two words", "en", None, 9)], COLS)
    for name, stage in cp.STAGES:
        assert stage(spark, odd, sf).collect() is not None, name
    assert quality.BASE_RULES and defaultdict
