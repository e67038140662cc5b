"""Exact dedup, mixing and WARC against brute force on small fixtures."""

import collections
import gzip
import hashlib
import random

import pytest
from pyspark.sql import functions as F

from hgpart.llm.common import connected_components
from hgpart.llm.exact_dedup import exact_dedup
from hgpart.llm.mixing import capped_unit, mix_sources
from hgpart.llm.warc import chunked, http_payload, parse_warc, read_warc, unchunked, warc_round_trip, write_warc

DOCS = "doc_id long, text string, source string, keep_id string, body string"


def docs_of(spark, rows):
    return spark.createDataFrame([(i, t, s, "x", "y") for i, t, s in rows], DOCS)


CASES = [(1, "Same Text", "a"), (2, "same text", "b"), (3, "SAME TEXT", None), (4, None, "a"), (5, "", "a"), (6, "É same", "a"), (7, "é same", "a"), (8, "x" * 300_000, "b"), (8, "x" * 300_000, "b"), (9, "other", "b"), (None, "other", "a"), (10, " other", "a")]


@pytest.mark.parametrize("bits", [16, 1, 0])
@pytest.mark.parametrize("keep", ["min", "max"])
def test_exact_dedup_matches_brute_force(spark, bits, keep):
    groups = collections.defaultdict(list)
    low = lambda t: (t or "").encode().lower()
    for i, t, _ in CASES:
        groups[low(t)].append(i)
    best = {k: {"min": min, "max": max}[keep]((i for i in v if i is not None), default=None) for k, v in groups.items()}
    want = sorted(((i, best[low(t)], len(groups[low(t)]), i == best[low(t)], hashlib.sha256(low(t)).hexdigest()) for i, t, _ in CASES), key=str)
    got = sorted((tuple(r) for r in exact_dedup(docs_of(spark, CASES), keep=keep, hash_bytes=bits).collect()), key=str)
    assert got == want


def test_exact_dedup_hot_groups(spark, monkeypatch):
    import hgpart.llm.common as E

    monkeypatch.setattr(E, "BROADCAST_ROWS", 1)
    monkeypatch.setattr(E, "HOT_ROWS", 3)
    rows = [(i, f"text {i % 7 if i % 2 else i}", "a") for i in range(60)]
    want = sorted((r["doc_id"], r["keep_id"], r["group_size"]) for r in exact_dedup(docs_of(spark, rows), keep="max").collect())
    groups = collections.defaultdict(list)
    for i, t, _ in rows:
        groups[t].append(i)
    assert want == sorted((i, max(groups[t]), len(groups[t])) for i, t, _ in rows)


def test_exact_dedup_empty(spark):
    assert exact_dedup(docs_of(spark, [])).collect() == []


def capped_targets(sizes, weights, total, most):
    """By hand: share, cap, share what is left again."""
    target, left, free = [0.0] * len(sizes), float(total), {i for i, x in enumerate(sizes) if x > 0}
    while free:
        unit = left / sum(weights[i] for i in free)
        over = {i for i in free if weights[i] * unit > most * sizes[i]}
        for i in over or free:
            target[i] = most * sizes[i] if over else weights[i] * unit
        left -= sum(target[i] for i in over)
        free = free - over if over else set()
    return target


def test_capped_targets(spark):
    rng = random.Random(2)
    for sizes in ([10, 10, 10], [1, 50, 49], [0, 0], [0, 7, 1, 900, 3, 2], [rng.randint(0, 50) ** 3 for _ in range(40)]):
        weights = [[5.0, 2.0, 1.0][i % 3] for i in range(len(sizes))]
        unit = capped_unit(spark.createDataFrame(list(zip(sizes, weights)), "source_size long, weight double"), 3.0)
        got = [min(w * unit, 3 * s) for s, w in zip(sizes, weights)]
        assert got == pytest.approx(capped_targets(sizes, weights, sum(sizes), 3))


def test_overlapping_constraints(spark):
    rng = random.Random(4)
    rows = [(i, "w " * rng.randint(1, 9), rng.choice("abc"), rng.choice(["x", "y"])) for i in range(3000)]
    got = mix_sources(spark.createDataFrame(rows, "doc_id long, text string, source string, lang string"), also=("lang",), carry=("source", "lang", "size")).toPandas()
    for column, values in (("source", "abc"), ("lang", "xy")):
        sizes = [int(got.loc[got[column] == v, "size"].sum()) for v in values]
        want = capped_targets(sizes, [5.0, 2.0, 1.0], sum(sizes), 3)
        for v, t in zip(values, want):
            own = got[got[column] == v]
            assert (own["size"] * own["rate"]).sum() == pytest.approx(t, rel=1e-6)
            assert abs(own["taken"].sum() - t) <= 0.03 * t
    # the tilt is a product of one factor a value
    rate = got.groupby(["source", "lang"])["rate"].agg(["min", "max"])
    assert (rate["max"] - rate["min"] < 1e-9).all()
    r = rate["min"]
    assert r["a", "x"] * r["b", "y"] == pytest.approx(r["a", "y"] * r["b", "x"], rel=1e-6)


def test_mix_hits_targets(spark, sf):
    docs = spark.read.parquet(f"{sf.replace('0.001', '0.01')}/documents.parquet")
    a = mix_sources(docs).toPandas().sort_values("doc_id").reset_index(drop=True)
    b = mix_sources(docs.repartition(7)).toPandas().sort_values("doc_id").reset_index(drop=True)
    assert a.equals(b)
    own = docs.toPandas().set_index("doc_id")["source"]
    a["source"] = a["doc_id"].map(own)
    each = a.groupby("source").agg(size=("size", "sum"), source_size=("source_size", "first"), target=("target", "first"), taken=("taken", "sum"))
    assert (each["size"] == each["source_size"]).all()
    assert (abs(each["taken"] - each["target"]) <= 0.01 * each["target"] + 20).all()
    assert (a["taken"] <= 3 * a["size"]).all()
    assert (a["taken"] == a["copies"] * a["size"]).all()
    assert each["target"].sum() == pytest.approx(each["size"].sum())
    texts = docs.toPandas().set_index("doc_id")["text"]
    assert all(len(texts[i].encode().split()) == s for i, s in zip(a["doc_id"], a["size"]))


def test_mix_edge_cases(spark):
    got = {r["doc_id"]: r for r in mix_sources(docs_of(spark, [(1, None, "a"), (2, "w " * 60, None), (3, "w " * 40, "b"), (4, "", None)])).collect()}
    assert got[1]["taken"] == 0 and got[1]["source_size"] == 0
    assert got[2]["source_size"] == 60 and got[4]["size"] == 0
    assert sum(r["target"] for i, r in got.items() if i in (1, 2, 3)) == pytest.approx(100)
    assert mix_sources(docs_of(spark, [])).collect() == []


def test_components(spark):
    edges = [(1, 2), (2, 3), (5, 4), (7, 7), (9, 8), (8, 10), (None, 3)] + [(100, i) for i in range(101, 160)] + [(i, i + 1) for i in range(200, 260)]
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert [got[i] for i in (1, 2, 3, 4, 5, 8, 9, 10)] == [1, 1, 1, 4, 4, 8, 8, 8]
    assert {got[i] for i in range(100, 160)} == {100} and {got[i] for i in range(200, 261)} == {200} and 7 not in got


PAGES = "page_id long, url string, html string, digest string"


def test_warc_round_trip(spark):
    long = "<p>" + "ü word " * 9000 + "WARC/1.1\r\n\r\n</p>"
    rows = [(1, "http://a/x y", "short", "d"), (2, None, None, "d"), (3, "http://a", "s" * 1000, "d"), (4, "http://b", "s" * 1000, "d"), (5, "u", long, "d"), (6, "v", long, "d"), (7, "w", "short", "d")]
    got = {r["page_id"]: r for r in warc_round_trip(spark.createDataFrame(rows, PAGES)).collect()}
    assert len(got) == 7
    for i, _, html, _ in rows:
        body = (html or "").encode()
        assert got[i]["payload_bytes"] == len(body) and got[i]["payload_digest"] == hashlib.sha1(body).hexdigest()
    assert {i: (r["record_type"], r["refers_to"]) for i, r in got.items() if r["record_type"] == "revisit"} == {3: ("revisit", 4), 5: ("revisit", 6)}


def test_warc_ids_null_or_repeated(spark):
    rows = [(1, "u", "a" * 2000, "d"), (1, "u", "a" * 2000, "d"), (None, "u", "a" * 2000, "d"), (2, "u", "b", "d")]
    got = [tuple(r) for r in warc_round_trip(spark.createDataFrame(rows, PAGES)).collect()]
    assert len(got) == 4 and sum(r[3] == "revisit" for r in got) == 2
    assert {r[4] for r in got if r[3] == "revisit"} == {1}
    assert warc_round_trip(spark.createDataFrame([], PAGES)).collect() == []


def test_warc_files_are_archives(spark, tmp_path):
    body = "z" * 40_000
    write_warc(spark.createDataFrame([(1, "http://a/", body, "d"), (2, "http://b/", "tiny", "d")], PAGES), str(tmp_path / "w"))
    records = [x for f in (tmp_path / "w").glob("*.gz") for x in parse_warc(f.read_bytes())]
    kinds = collections.Counter(h["warc-type"] for h, _ in records)
    assert kinds == {"response": 2, "continuation": 2}
    assert gzip.decompress(next(f for f in (tmp_path / "w").glob("*.gz") if f.stat().st_size > 30).read_bytes()).startswith(b"WARC/1.1\r\n")
    got = {r["uri"]: bytes(r["payload"]) for r in read_warc(spark, str(tmp_path / "w")).collect()}
    assert got == {"http://a/": body.encode(), "http://b/": b"tiny"}


def test_chunked_framing():
    for body in (b"", b"a", b"x" * 5000, bytes(range(256)) * 40):
        assert unchunked(chunked(body, 97)) == body
    assert unchunked(b"3;ext=1\r\nabc\r\n0\r\nTrailer: x\r\n\r\n") == b"abc"
    with pytest.raises(ValueError):
        unchunked(b"5\r\nabc\r\n0\r\n\r\n")
    assert http_payload(b"HTTP/1.1 200 OK\r\nTransfer-Encoding: chunked\r\n\r\n" + chunked(b"hey"))[0] == b"hey"


def test_broken_archives_raise():
    head = b"WARC/1.1\r\nWARC-Type: response\r\nContent-Length: 10\r\n\r\n"
    with pytest.raises(ValueError):
        list(parse_warc(head + b"short"))
    with pytest.raises(ValueError):
        list(parse_warc(b"HTTP/1.1\r\nContent-Length: 1\r\n\r\nx\r\n\r\n"))
    assert F is not None
