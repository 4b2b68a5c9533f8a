"""WARC round trips, broken archives, and exact search."""

import gzip
import hashlib
import random

import numpy as np
import pytest

from overlapsolve.llm import topk_search, warc


def pages_of(spark, rows):
    return spark.createDataFrame(rows, "page_id long, url string, html string, digest string, salt long")


def test_round_trip(spark, tmp_path):
    r = random.Random(1)
    long = ["".join(r.choice("abc é\n") for _ in range(1500)) for _ in range(5)]
    texts = [r.choice(long) for _ in range(60)] + ["short", "short", None, "", "x" * 999, "x" * 999, "y" * 1000, "y" * 1000]
    pages = pages_of(spark, [(k, f"http://h/{k}\r\nX: y" if k % 7 else None, t, "d", 1) for k, t in enumerate(texts)])
    path = str(tmp_path / "w")
    warc.write(pages, path, part_bytes=4000)
    archives = spark.read.parquet(path)
    got = {x.page_id: x for x in warc.read_back(archives, payloads=True).collect()}
    assert len(got) == len(texts)
    for k, t in enumerate(texts):
        raw = (t or "").encode()
        last = max(j for j, u in enumerate(texts) if (u or "").encode() == raw)
        revisit = len(raw) >= 1000 and last != k
        assert (got[k].record_type, got[k].refers_to) == (("revisit", last) if revisit else ("response", None))
        assert got[k].payload_bytes == len(raw) and got[k].payload_digest == hashlib.sha1(raw).hexdigest()
        assert got[k].payload == (b"" if revisit else raw)
    files = warc.export_files(archives, str(tmp_path / "files"))
    records = [x for f in files for x in warc.read(warc.file_chunks(f, 100))]
    assert len(records) == len(texts) and all(gzip.open(f).read(9) == b"WARC/1.1\r" for f in files)


def test_empty_and_repeated(spark, tmp_path):
    warc.write(pages_of(spark, []), str(tmp_path / "e"))
    assert warc.read_back(spark.read.parquet(str(tmp_path / "e"))).count() == 0
    warc.write(pages_of(spark, [(4, "u", "z" * 2000, "d", 1), (4, "u", "z" * 2000, "d", 1), (None, "u", "z" * 2000, "d", 1)]), str(tmp_path / "r"))
    assert {(x.page_id, x.record_type) for x in warc.read_back(spark.read.parquet(str(tmp_path / "r"))).collect()} == {(4, "response"), (None, "response")}


def test_broken_archives():
    whole = warc.encode(1, "u", b"payload" * 50, None)
    assert [x.payload for x in warc.read([whole[:10], whole[10:] + whole])] == [b"payload" * 50] * 2
    with pytest.raises(ValueError, match="within a member"):
        list(warc.read([whole[:-12]]))
    plain = gzip.decompress(whole)
    with pytest.raises(ValueError, match="digest"):
        list(warc.read([gzip.compress(plain.replace(b"payloadpayload", b"payloadPayload", 1))]))
    with pytest.raises(ValueError, match="length"):
        list(warc.read([gzip.compress(plain[:-30])]))
    with pytest.raises(ValueError, match="no WARC"):
        list(warc.read([gzip.compress(b"hello")]))


def brute(vectors, every, k, scale=1024):
    ok = {}
    for i, v in vectors:
        if i is not None and v is not None and all(x is not None and np.isfinite(x) for x in v):
            ok.setdefault(i, []).append([int(np.floor(scale * x)) for x in v])
    out = set()
    for q in ok:
        if q % every == 0:
            best = min(ok[q])
            scores = sorted((-sum(a * b for a, b in zip(best, v, strict=False)), i) for i, vs in ok.items() if i != q for v in vs)[:k]
            out |= {(q, rank, i, -s) for rank, (s, i) in enumerate(scores, 1)}
    return out


def test_search(spark):
    r = random.Random(6)
    unit = lambda: [r.choice([-0.5, 0.25, 0.0, r.uniform(-1, 1)]) for _ in range(6)]
    same = unit()
    rows = [(k, same if k % 3 == 0 else unit()) for k in range(200)]
    rows += [(1000, None), (1001, [None] * 6), (1010, [float("nan")] * 6), (1020, [float("inf")] * 6), (None, unit()), (300, unit()[:3]), (7, unit()), (310, []), (320, [1e9] * 6)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(5)
    got = {(x.query_id, x["rank"], x.vec_id, x.score) for x in topk_search.search(df, every=10, k=4).collect()}
    assert got == brute(rows, 10, 4)
    assert topk_search.search(df.limit(0), 10, 4).count() == 0
    few = spark.createDataFrame(rows[:3], "vec_id long, embedding array<double>")
    assert topk_search.search(few, 10, 4).count() == 2


def test_max_score_prunes_without_loss():
    rng = np.random.default_rng(4)
    vectors = np.floor(1024 * rng.normal(size=(3000, 32)) / 6).astype(np.int64)
    shard = topk_search.Shard(np.arange(3000), vectors)
    for q in range(0, 3000, 300):
        ids, scores = shard.best(vectors[q], q, 10)
        s = vectors @ vectors[q]
        order = [i for i in np.lexsort((np.arange(3000), -s)) if i != q][:10]
        assert ids.tolist() == order and scores.tolist() == s[order].tolist()
