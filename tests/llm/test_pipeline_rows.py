import hashlib
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tagroute.llm import piece_sampling, toxicity_ws

TINY = "/root/testdata/sf0.001"
ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
BASE = (
    (re.compile(r"(?i:password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)"), 1, 8), (re.compile("AKIA[A-Z0-9]+"), 0, 16),
    (re.compile("[0-9a-f]+"), 0, 32), (re.compile("[A-Za-z0-9+/_-]{24,}"), 0, 24),
)


def _words(text):
    return ALNUM.findall(text.translate({c: c + 32 for c in range(65, 91)}))


def _shingles(text, k=5):
    w = (text or "").lower().split()
    return {tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))} if w else set()


def test_near_duplicates_by_row_against_brute_force(spark, make):
    base = {n: [f"{n}word{chr(97 + i // 26)}{chr(97 + i % 26)}" for i in range(60)] for n in ("a", "b", "c", "d")}
    text = {n: " ".join(w) for n, w in base.items()}
    near = {n: " ".join([*w[:-1], "other"]) for n, w in base.items()}
    rows = [(3, text["a"]), (7, near["a"]), (7, text["b"]), (8, text["c"]), (8, near["c"]), (9, text["d"]), (9, text["d"]), (None, text["a"]), (10, None), (11, "")]
    got = sorted(((r.doc_id, r.text) for r in corpus_pipeline.near_duplicates(spark, make(rows), "").collect()), key=repr)
    grouped = [(i, t) for i, t in rows if i is not None and t]
    similar = lambda s, t: len(s & t) >= 0.8 * len(s | t)
    groups = []
    for row in grouped:
        met = [g for g in groups if any(similar(_shingles(row[1]), _shingles(t)) for _, t in g)]
        groups = [g for g in groups if g not in met] + [[row, *(r for g in met for r in g)]]
    assert [r for r in got if r[0] is None or not r[1]] == sorted([r for r in rows if r[0] is None or not r[1]], key=repr)
    kept = [r for r in got if r[0] is not None and r[1]]
    assert len(kept) == len(groups) == 4
    for g in groups:
        mine = [r for r in kept if r in g]
        assert len(mine) == 1 and mine[0][0] == min(i for i, _ in g)


def _found_secrets(text):
    out = []
    for n, (pattern, group, least) in enumerate(BASE):
        for m in pattern.finditer(text):
            v = m.group(group)
            if len(v) >= least and (n < 3 or all(re.search(c, v) for c in ("[A-Z]", "[a-z]", "[0-9]"))):
                out.append((n, *m.span(), v))
    return out


def _masked(text, spans):
    hidden = [False] * len(text)
    starts = set()
    at = 0
    for _, a, b, _ in sorted(spans, key=lambda s: (s[1], s[2])):
        if b > at:
            if a >= at:
                starts.add(a)
            hidden[a:b] = [True] * (b - a)
            at = b
    return "".join(("[SECRET]" if i in starts else "") + ("" if h else c) for i, (c, h) in enumerate(zip(text, hidden, strict=True)))


def test_whole_pipeline_against_plain_python(spark):
    docs = [r.asDict() for r in spark.read.parquet(f"{TINY}/documents.parquet").collect()]
    model = toxicity_ws.train(spark.read.parquet(f"{TINY}/documents.parquet"), spark.read.parquet(f"{TINY}/labels.parquet"))
    docs = [d for d in docs if model.score([(d["text"] or "").encode()])[0] < 0.5]
    sets = {d["doc_id"]: _shingles(d["text"]) for d in docs}
    root = {i: i for i in sets}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(sets)
    for n, a in enumerate(ids):
        for b in ids[:n]:
            if sets[a] and sets[b] and len(sets[a] & sets[b]) * 100 >= 80 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    docs = [d for d in docs if find(d["doc_id"]) == d["doc_id"]]
    windows = set()
    for r in spark.read.parquet(f"{TINY}/benchmark.parquet").collect():
        w = _words(r.text or "")
        windows |= {tuple(w[i : i + 10]) for i in range(max(1, len(w) - 9))} if w else set()
    sizes = {len(w) for w in windows}
    held = lambda w: any(tuple(w[i : i + n]) in windows for n in sizes for i in range(len(w) - n + 1))
    docs = [d for d in docs if not held(_words(d["text"] or ""))]
    owners = {}
    for d in docs:
        for *_, v in _found_secrets(d["text"] or ""):
            owners.setdefault(v, set()).add((d["source"], d["lang"]))
    live = {v for v, of in owners.items() if len({o for o, _ in of}) <= 1 and len(of) <= 2}
    for d in docs:
        d["text"] = _masked(d["text"] or "", [s for s in _found_secrets(d["text"] or "") if s[0] < 3 or s[3] in live])
    pieces = piece_sampling.Pieces.load(piece_sampling.default_model())
    keys = {r.i: r.k for r in spark.createDataFrame([(d["doc_id"],) for d in docs], "i long").select("i", F.xxhash64(F.col("i").cast("string")).alias("k")).collect()}
    expected = []
    for d in docs:
        raw = d["text"].encode()
        (found,) = piece_sampling.encode_texts(pieces, [raw], np.array([keys[d["doc_id"]]]), 17)
        assert piece_sampling.decode_ids(pieces, [found]) == [raw]
        expected.append((d["doc_id"], len(raw), len(found), hashlib.sha256(found.astype("<i4").tobytes()).hexdigest(), True))
    got = [tuple(r) for r in corpus_pipeline.run(spark, TINY).collect()]
    assert 20 < len(got) < 200 and sorted(got) == sorted(expected)


@pytest.mark.parametrize("name", [n for n, _ in corpus_pipeline.STAGES])
def test_stages_take_odd_rows(spark, make, name):
    """Nulls, empty and long texts, repeated rows, further columns, empty tables: clean rows stay, one by one."""
    stage = dict(corpus_pipeline.STAGES)[name]
    rows = [(1, None), (2, ""), (3, " \t"), (None, "a text without an id"), (4, "word " * 30_000), (5, "plain words of a clean text"), (6, "token = abcdefgh1234 here"), (None, None)]
    odd = make(rows).withColumn("lang", F.lit(None).cast("string")).withColumn("source", F.when(F.col("doc_id") > 4, F.col("source"))).withColumn("n_chars", F.lit(None).cast("long"))
    again = odd.unionByName(odd.filter("doc_id = 5"))
    got = stage(spark, again, TINY).collect()
    if name == "pieces":
        assert len(got) == 9 and all(r.lossless for r in got)
    else:
        assert tuple(got[0].asDict()) == corpus_pipeline.COLUMNS
        expected = [r for r in rows if r[0] != 5] + [(5, rows[5][1])] * (1 if name == "near_duplicates" else 2)
        if name == "secrets":
            expected = [(i, "[SECRET] here" if i == 6 else t) for i, t in expected]
        assert sorted([(r.doc_id, r.text) for r in got], key=repr) == sorted(expected, key=repr)
        assert all(r.lang is None for r in got)
    none = stage(spark, make([]), TINY)
    assert none.count() == 0
