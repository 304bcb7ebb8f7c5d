import hashlib
import itertools
import zlib

import numpy as np
import pytest

from tagroute.llm import jpeg_thumbs, quality_pu, role_repair, toxicity_ws, warc_revisit

SMALL = "/root/testdata/sf0.01"


def test_jpeg_payloads():
    rng = np.random.default_rng(1)
    for p in [bytes(rng.integers(0, 256, 192 * k, dtype=np.uint8)) for k in (1, 2, 17)] + [b"\xff" * 192, b"\x00\xff" * 960]:
        (picture, thumb), *_ = jpeg_thumbs.decode([jpeg_thumbs.encode_payload(p)])[0]
        assert thumb.tobytes() == p and picture.width * picture.height == 64 * len(p)
    with pytest.raises(ValueError):
        jpeg_thumbs.encode_payload(b"")


def test_jpeg_with_ac_and_subsampled_colour():
    """A 4:2:0 picture with AC coefficients, coded here bit by bit."""
    dc = {s: (c, n) for c, n, s in jpeg_thumbs._codes(jpeg_thumbs._DC_LENGTHS, jpeg_thumbs._DC_SYMBOLS)}
    ac_lengths, ac_symbols = (0, 3, *[0] * 14), (0x00, 0x01, 0x32)
    ac = {s: (c, n) for c, n, s in jpeg_thumbs._codes(ac_lengths, ac_symbols)}
    rng = np.random.default_rng(2)
    luma = rng.integers(-100, 100, (4, 4))
    bits, pred = "", [0, 0, 0]

    def put(table, symbol, value, k):
        nonlocal bits
        code, n = table[symbol]
        bits += format(code, f"0{n}b") + (format(value if value >= 0 else value + (1 << k) - 1, f"0{k}b") if k else "")

    for my, mx in itertools.product(range(2), range(2)):
        for c, level in [(0, int(luma[2 * my + y, 2 * mx + x])) for y in range(2) for x in range(2)] + [(1, 5), (2, -7)]:
            d, pred[c] = level - pred[c], level
            put(dc, abs(d).bit_length(), d, abs(d).bit_length())
            put(ac, 0x01, 1, 1)
            put(ac, 0x32, -2, 2)
            put(ac, 0x00, 0, 0)
    bits += "1" * (-len(bits) % 8)
    scan = bytes(int(bits[i : i + 8], 2) for i in range(0, len(bits), 8)).replace(b"\xff", b"\xff\x00")
    seg = jpeg_thumbs._segment
    size = bytes([8, 0, 32, 0, 32, 3, 1, 0x22, 0, 2, 0x11, 0, 3, 0x11, 0])
    data = b"\xff\xd8" + seg(0xDB, bytes([0, 8, *[1] * 63])) + seg(0xC0, size) + seg(0xC4, bytes([0, *jpeg_thumbs._DC_LENGTHS, *jpeg_thumbs._DC_SYMBOLS]) + bytes([0x10, *ac_lengths, *ac_symbols])) + seg(0xDA, bytes([3, 1, 0, 2, 0, 3, 0, 0, 63, 0])) + scan + b"\xff\xd9"
    (_, thumb), *_ = jpeg_thumbs.decode([data])[0]
    assert (thumb == np.clip(luma + 128, 0, 255)).all()


def test_jpeg_columns(spark, make):
    docs = make([(1, "abc"), (2, None), (3, ""), (1, "abc"), (4, "é" * 500)])
    rows = jpeg_thumbs.features(jpeg_thumbs.store(docs)).collect()
    by = {r.id: r for r in rows}
    assert len(rows) == 5 and by[2].payload_bytes == 192 and by[2].payload_sha256 == by[3].payload_sha256 and by[4].n_bytes == 1000 and by[4].payload_bytes == 1152
    texts = {1: "abc", 2: "", 3: "", 4: "é" * 500, 5: "x y\n" * 30_000}
    stored = {r.id: r.media for r in jpeg_thumbs.store(make([(i, t or None) for i, t in texts.items()])).collect()}
    for r in jpeg_thumbs.features(jpeg_thumbs.store(make(list(texts.items())))).collect():
        raw = texts[r.id].encode()
        payload = raw + b" " * (-len(raw) % 192 if raw else 192)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]))
        assert (r.media_bytes, r.media_sha256) == (len(stored[r.id]), hashlib.sha256(stored[r.id]).hexdigest()) and r.feature
        assert b"".join(t.tobytes() for _, t in jpeg_thumbs.decode([bytes(stored[r.id])])[0]) == payload
    good = jpeg_thumbs.thumbnails(spark.createDataFrame([(1, stored[4], "x"), (1, stored[4], "y")], "id long, media binary, width string")).collect()
    assert len(good) == 2 and good[0].error is None and good[0].width * good[0].height == 64 * 1152 and good[0] == good[1]
    bad = spark.createDataFrame([(1, b"no"), (2, None)], "id long, media binary")
    assert all(r.error for r in jpeg_thumbs.thumbnails(bad).collect())
    assert jpeg_thumbs.features(jpeg_thumbs.store(make([]))).count() == 0


def test_role_repair_costs_are_least():
    """All sequences of up to four turns against every choice of states."""
    for n in range(1, 5):
        for given in itertools.product(range(4), repeat=n):
            best = min(
                sum(role_repair.STEPS[g][a][b][0] if role_repair.STEPS[g][a][b] else 10**6 for g, a, b in zip(given, (0, *states[:-1]), states, strict=True)) + role_repair.ENDINGS[states[-1]][0]
                for states in itertools.product(range(4), repeat=n)
            )
            states, cost = role_repair.path(list(given), 0, None)
            assert cost == best
            assert (np.array([role_repair.matrix(list(given))[0, s] + role_repair.ENDINGS[s][0] for s in range(4)])).min() == best


def test_role_repair_rows(spark):
    rows = [(1, 0, "user", "hi"), (1, 1, "User", "more"), (1, 2, None, "x"), (2, 0, "system", "s"), (2, 1, "assistant", None), (None, None, "user", "n"), (3, 0, "user", "<|im_end|>")] + [(9, i, "user" if i % 2 == 0 else "assistant", f"t{i}") for i in range(400)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    out = role_repair.repair(df)
    got = out.collect()
    assert len(got) == len(rows)
    by = {}
    for r in sorted(got, key=lambda r: (r.conv_id is not None, r.conv_id, r.turn)):
        by.setdefault(r.conv_id, []).append(r)
    text = "".join(r.rendered for r in by[9])
    assert text.count("<|im_start|>") == 400 and text.endswith("<|im_end|>\n") and all(r.action.startswith("keep") for r in by[9])
    assert [r.action for r in by[1]] == ["keep", "merge", "relabel"]
    assert [r.action for r in by[2]] == ["relabel", "keep"] and "< |im_end|>" in by[3][0].rendered
    assert role_repair.repair(df.limit(0)).count() == 0


def test_revisits(spark):
    rows = [
        (1, "response", "http://A.com/x/", 10, "e1", None, "d1", {"ETag": "e1", "Server": "s"}), (2, "revisit", "https://www.a.com:443/x#f", 20, "e1", None, None, {"Date": "2", "Server": "t"}), (3, "revisit", "http://a.com/x", 5, "e1", None, None, None),
        (4, "revisit", "http://a.com/x?utm_source=1", 30, "e2", None, None, {}), (5, "revisit", "http://a.com/x", 40, None, None, None, {}), (6, "revisit", None, 50, "e1", None, None, {}), (7, "metadata", "http://a.com/x", 60, None, None, None, {}), (2, "revisit", "https://www.a.com:443/x#f", 20, "e1", None, None, {"Date": "2", "Server": "t"}),
    ]
    df = spark.createDataFrame(rows, "rec_id long, rec_type string, url string, ts long, etag string, last_modified string, digest string, headers map<string,string>")
    got = warc_revisit.resolve(df).collect()
    assert sorted((r.rec_id, r.status) for r in got) == [(2, "resolved"), (2, "resolved"), (3, "orphan"), (4, "mismatch"), (5, "unchecked"), (6, "orphan")]
    assert next(r.headers for r in got if r.rec_id == 2) == {"ETag": "e1", "Server": "s", "Date": "2"}
    assert warc_revisit.resolve(df.limit(0)).count() == 0


def test_classifiers_hold_out(spark, make):
    from pyspark.sql import functions as F

    docs, labels = spark.read.parquet(f"{SMALL}/documents.parquet"), spark.read.parquet(f"{SMALL}/labels.parquet")
    toxic = toxicity_ws.train(docs, labels)
    got = toxicity_ws.score(docs, toxic).join(labels.withColumnRenamed("doc_id", "id"), "id").filter(F.crc32(F.col("id").cast("string")) % 5 == 0).collect()
    assert np.mean([(r.score >= 0.5) == (r.toxic == 1) for r in got]) > 0.9
    good = quality_pu.train(docs, labels)
    got = quality_pu.score(docs, good).join(labels.withColumnRenamed("doc_id", "id"), "id").filter(F.crc32(F.col("id").cast("string")) % 4 == 2).collect()
    assert np.mean([(r.score >= 0.7) == (r.quality == 1) for r in got]) > 0.9
    odd = make([(1, None), (2, ""), (3, "x " * 9000), (3, "x " * 9000), (None, "word")])
    for module, model in ((toxicity_ws, toxic), (quality_pu, good)):
        rows = module.score(odd, model).collect()
        assert len(rows) == 5 and all(0 <= r.score <= 1 for r in rows) and module.score(make([]), model).count() == 0
    no_labels = labels.limit(0)
    assert toxicity_ws.score(odd, toxicity_ws.train(docs, no_labels)).filter("score >= 0.5").count() == 0
    assert quality_pu.train(docs, no_labels) is None
    # no label but 1 counts: without the zeros, and with them flipped to null, the scores are the same
    for other in (labels.filter("quality = 1"), labels.withColumn("quality", F.when(F.col("quality") == 1, 1))):
        again = quality_pu.train(docs, other)
        assert again.prior == good.prior and (again.weight == good.weight).all() and again.shift == good.shift


def test_nnpu_risk_and_prior():
    rng = np.random.default_rng(0)
    p, n = rng.normal(2, 1, (400, 2)).astype(np.float32), rng.normal(-2, 1, (400, 2)).astype(np.float32)
    mixed = np.concatenate((rng.normal(2, 1, (300, 2)), n[:200])).astype(np.float32)
    w, b, risks = quality_pu.fit_nnpu(p, mixed, 0.6)
    assert risks[-1] < risks[0] and ((p @ w + b) > 0).mean() > 0.95 and ((n @ w + b) < 0).mean() > 0.9
    assert abs(quality_pu.estimate_prior(p @ w + b, mixed @ w + b) - 0.6) < 0.1


def test_label_model_finds_accuracies_and_correlations():
    rng = np.random.default_rng(3)
    y = rng.random(4000) < 0.3
    votes = np.stack([np.where(y, rng.random(4000) < 0.7, rng.random(4000) < 0.02).astype(float) for _ in range(5)] + [np.zeros(4000)] * 6, 1)
    votes[:, 4] = votes[:, 3]  # one voter repeats another
    post, learned = toxicity_ws.label_model(votes)
    assert ((post > 0.5) == y).mean() > 0.95
    assert learned["correlation"][3, 4] > 0.6 > abs(learned["correlation"][0, 1])
    assert learned["weight"][4] < learned["weight"][0]
