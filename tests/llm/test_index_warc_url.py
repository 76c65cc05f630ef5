"""Bit-sliced search, archives and URL rules."""

import io
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from evenset.llm import bit_topk, shared, url_templates, warc


def best(values, ids, query, own, k):
    score = values @ query
    keep = ids != own
    turn = np.lexsort((ids[keep], -score[keep]))[:k]
    return [(int(ids[keep][i]), int(score[keep][i])) for i in turn]


@pytest.mark.parametrize("n,dim,spread", [(1, 3, 9), (64, 4, 300), (700, 16, 120), (300, 8, 1), (500, 5, 3)])
def test_search_block_exact(n, dim, spread):
    rng = np.random.default_rng(n)
    values = rng.integers(-spread, spread + 1, (n, dim))
    values[n // 2 :] = values[n // 2 :][:1]  # a third and more of equal rows
    ids = rng.permutation(n * 3)[:n].astype(np.int64)
    queries = np.vstack([values[: min(n, 20)], np.zeros((1, dim), np.int64), -values[:1]])
    own = np.append(ids[: min(n, 20)], [-1, -2])
    found = {}
    for q, i, s in bit_topk.search_block(bit_topk.SliceIndex(values), ids, queries, own, 5):
        found.setdefault(q, []).append((i, s))
    for q, o in zip(queries, own):
        assert found.get(int(o), []) == best(values, ids, q, o, 5)


def test_top_k_corner_rows(spark):
    rows = [
        (0, [1.0, 0.0], "x"),
        (50, [0.5, 0.5], "x"),
        (1, None, "x"),
        (2, [None, 1.0], "x"),
        (3, [float("nan"), 1.0], "x"),
        (4, [float("inf"), 1.0], "x"),
        (5, [0.5, 0.5], "x"),
        (6, [0.5, 0.5], "x"),
    ]
    data = spark.createDataFrame(rows, "vec_id long, embedding array<float>, score string")
    codes = bit_topk.quantise(data)
    got = bit_topk.top_k(codes, codes.where("vec_id % 50 = 0")).orderBy("query_id", "rank").collect()
    assert [tuple(r) for r in got if r["query_id"] == 50] == [(50, 1, 0, 32768), (50, 2, 5, 32768), (50, 3, 6, 32768)]
    assert bit_topk.top_k(codes.limit(0), codes.limit(0)).count() == 0
    far = spark.createDataFrame([(0, [1e8, 0.5]), (1, [0.5, 0.5]), (2, [-1e8, 1.0])], "vec_id long, embedding array<float>")
    far = bit_topk.quantise(far)
    got = [tuple(r) for r in bit_topk.top_k(far, far.where("vec_id = 1")).orderBy("rank").collect()]
    big = 256 * 10**8
    assert got == [(1, 1, 0, 128 * big + 128 * 128), (1, 2, 2, -128 * big + 128 * 256)]


def test_repeated_ids_and_odd_lengths_take_part_once(spark):
    rows = [(50, [1.0, 0.5]), (50, [1.0, 0.5]), (50, [1.5, 0.5]), (1, [1.0, 1.0]), (1, [0.5, 1.0]), (2, [1.0, 0.0]), (3, [1.0]), (None, [2.0, 2.0]), (4, [])]
    data = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    for turn in (data.coalesce(1), data.orderBy(F.desc("embedding")).coalesce(1)):
        codes = bit_topk.one_length(bit_topk.quantise(turn))
        got = [tuple(r) for r in bit_topk.top_k(codes, codes.where("vec_id % 50 = 0")).orderBy("rank").collect()]
        assert got == [(50, 1, 2, 65536), (50, 2, 1, 65536 // 2 + 32768)] or got == [(50, 1, 1, 65536), (50, 2, 2, 65536)]


def test_warc_round_trip(spark):
    long = "é漢" * 100_000
    rows = [(5, "http://a/1", "x" * 99), (6, "http://a/2", "x" * 99), (9, "u", long), (7, "u", long), (8, None, long)]
    rows += [(1, "u\r\nX: y", None), (2, "u", ""), (3, "u", "\r\n\r\nWARC/1.1" * 20), (None, "u", long)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("payload", F.lit(3))
    got = {r["page_id"]: r for r in warc.round_trip(pages.repartition(3)).collect()}
    assert len(got) == len(rows)
    assert got[7]["record_type"] == "response" and got[7]["refers_to"] is None
    assert {i: (got[i]["record_type"], got[i]["refers_to"]) for i in (8, 9, None)} == dict.fromkeys((8, 9, None), ("revisit", 7))
    assert got[5]["record_type"] == got[6]["record_type"] == "response"
    assert got[9]["payload_bytes"] == len(long.encode()) and got[1]["payload_bytes"] == 0
    assert warc.round_trip(pages.limit(0)).count() == 0


def test_reader_is_incremental_and_strict():
    record = lambda i, body: warc.record_bytes(str(i), "u", body, warc.hashlib.sha256(body).hexdigest(), None, i)
    bodies = [random.Random(i).randbytes(i * 7000) for i in range(40)]
    raw = b"".join(record(i, b) for i, b in enumerate(bodies))
    assert [warc.parse_record(m)[1] for m in warc.read_members(io.BytesIO(raw))] == bodies
    with pytest.raises(ValueError):
        list(warc.read_members(io.BytesIO(raw[:-5])))
    member = next(warc.read_members(io.BytesIO(record(1, b"hello"))))
    with pytest.raises(ValueError):
        warc.parse_record(member.replace(b"hello", b"hullo"))
    with pytest.raises(ValueError):
        warc.parse_record(member.replace(b"Content-Length: 5", b"Content-Length: 4"))


def test_url_rules(spark):
    rows = [
        (1, "http://COM/en/1"),
        (2, "https://www.example.com/en/77?q=/x#y"),
        (3, "http://xcom/en/1"),
        (4, "http://a.net/de/8"),
        (5, "http://example.net/de/8x"),
        (6, None),
        (7, "no scheme/en/"),
        (8, "http://a.com"),
        (9, "http://a.com?x=/en/"),
        (10, "a://b.org/es/://c/d"),
    ]
    pages = spark.createDataFrame(rows, "page_id long, url string").withColumn("host", F.lit(1)).withColumn("rule", F.lit(2))
    got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_templates.judge_urls(pages).collect()}
    assert got[1] == ("com", "/en/1", "com/en/", "block")
    assert got[2] == ("www.example.com", "/en/77", "example.com/en/7", "allow")
    assert got[3][2:] == (None, "allow") and got[4][2:] == ("net/de/", "block")
    assert got[5][2:] == ("example.net/de/8", "allow")
    assert got[6] == got[7] == ("", "", None, "allow")
    assert got[8][:2] == ("a.com", "") and got[9][:2] == ("a.com", "")
    assert got[10] == ("b.org", "/es/://c/d", "org/es/", "block")
    assert url_templates.judge_urls(pages.limit(0)).count() == 0


def test_contract_rules_hold_word_for_word(spark):
    said = "block com/en/, allow example.com/en/7, allow net/de/, block example.net/de/8, block org/es/"
    assert url_templates.RULES == tuple(tuple(x.split(" ")) for x in said.split(", "))
    hosts = ("a.com/en/1", "example.com/en/7", "a.net/de/8", "www.example.net/de/80", "example.net/de/7", "b.org/es/")
    pages = spark.createDataFrame([(i, f"http://{u}") for i, u in enumerate(hosts)], "page_id long, url string")
    got = [(r["rule"], r["verdict"]) for r in url_templates.judge_urls(pages).orderBy("page_id").collect()]
    assert got == [
        ("com/en/", "block"), ("example.com/en/7", "allow"), ("net/de/", "allow"), ("example.net/de/8", "block"),
        ("net/de/", "allow"), ("org/es/", "block"),
    ]


def test_url_templates_reject_by_purity(spark):
    rules = tuple(("block", f"h.org/shop/{i}") for i in range(1, 10)) + (("allow", "h.org/blog/1"),)
    rows = [(i, f"http://h.org/shop/{i % 10}{i}") for i in range(200)] + [(1000 + i, f"http://h.org/blog/{i}") for i in range(50)]
    pages = spark.createDataFrame(rows, "page_id long, url string")
    out = url_templates.judge_urls(pages, rules=rules)
    free = {r["page_id"]: r["verdict"] for r in out.where("rule is null").collect()}
    assert free and all(v == ("block" if i < 1000 else "allow") for i, v in free.items())
    many = rules + tuple(("block", f"x{i}.org/a") for i in range(300))
    assert url_templates.judge_urls(pages, rules=many).exceptAll(out).count() == 0


def test_url_rules_do_not_depend_on_their_number(spark):
    # equally long rules, one rule with both verdicts, and a rule without a path
    rules = (("allow", "a.com/b"), ("block", "com/b/x"), ("block", "b.org/k"), ("allow", "b.org/k"), ("block", "c.net"))
    rows = [(1, "http://a.com/b/xx"), (2, "http://b.org/k"), (3, "http://c.net"), (4, "http://w.c.net/z"), (5, "http://xc.net/z")]
    pages = spark.createDataFrame(rows, "page_id long, url string")
    for extra in (0, 5, 1000):
        more = rules + tuple(("block", f"x{i}.org/a") for i in range(extra))
        got = {r["page_id"]: (r["rule"], r["verdict"]) for r in url_templates.judge_urls(pages, rules=more).collect()}
        assert got == {1: ("a.com/b", "allow"), 2: ("b.org/k", "allow"), 3: ("c.net", "block"), 4: ("c.net", "block"), 5: (None, "allow")}


def test_url_tree_is_deep_and_keeps_constants(spark):
    deep = "/".join("k" * (i % 7 + 1) for i in range(400))
    rules = tuple(("block", f"h.org/{deep}/spam/{i}") for i in range(1, 8)) + tuple(("block", f"w.org/es/{i}") for i in range(1, 8))
    rows = [(i, f"http://h.org/{deep}/{'spam' if i % 2 else 'good'}/{i}") for i in range(100)]
    # forty first segments, one of them blocked and frequent
    rows += [(1002 + i, f"http://w.org/{'es' if i % 3 else 'x' + chr(97 + i % 40 // 26) + chr(97 + i % 26)}/{i}") for i in range(300)]
    rows += [(5000, "http://long.org/" + "/".join("abcdefghij" for _ in range(20000)))]
    rows += [(9000 + i, "http://same.org/p/q") for i in range(5)]
    pages = spark.createDataFrame(rows, "page_id long, url string")
    got = {r["page_id"]: r for r in url_templates.judge_urls(pages, rules=rules).collect()}
    assert len(got) == len(rows)
    free = {i: r["verdict"] for i, r in got.items() if r["rule"] is None}
    for i, v in free.items():
        bad = (i < 1000 and i % 2) or (1002 <= i < 1302 and i % 3)
        assert v == ("block" if bad else "allow"), got[i]
    assert any(i < 1000 and i % 2 for i in free) and any(1002 <= i < 1302 and i % 3 for i in free)
    assert len({got[9000 + i]["template"] for i in range(5)}) == 1


def test_hot_keys_join_alike(spark):
    left = spark.range(3000).select(F.when(F.col("id") < 2000, 7).otherwise(F.col("id")).alias("k"), "id")
    right = left.groupBy("k").agg(F.count("*").alias("w"))
    got = shared.join_weighted(left, right, ["k"], "w", 3000, floor=10)
    assert "BroadcastHashJoin" in got._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, left.join(right, "k").collect()))


def test_pipeline_odd_rows(spark):
    import corpus_pipeline as pipe

    body = " ".join(f"word{i}" for i in range(40))
    rows = [(1, body, "en", "s"), (2, body, "en", "s"), (None, body + " more", "en", None), (3, None, "en", "s"), (3, "", None, "s")]
    rows += [(4, " ".join(f"long{i}" for i in range(30000)), "de", "s"), (5, "short text", "de", "t")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    for c in ("__size", "__i", "row", "copies", "place", "node", "kept", "host", "__gone"):
        docs = docs.withColumn(c, F.lit("clash"))
    for start in (docs, docs.limit(0)):
        now = start
        for name, stage in pipe.STAGES:
            out = stage(spark, now, "/root/testdata/sf0.001")
            if name != "pack":
                assert out.columns == docs.columns
                now = spark.createDataFrame(out.collect(), docs.schema)
        packed = out.toPandas()
        if start is docs:
            assert set(packed["doc_id"].dropna()) == {1, 4} and packed["doc_id"].isna().any()
        else:
            assert len(packed) == 0


def test_pipeline(spark):
    import corpus_pipeline as pipe

    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, sizes = docs.columns, [docs.count()]
    for i, (_, stage) in enumerate(pipe.STAGES):
        docs = spark.createDataFrame(stage(spark, docs, sf).toPandas(), None if i == 4 else docs.schema)
        sizes.append(docs.count())
        assert i == 4 or docs.columns == columns
    assert sizes[0] > sizes[1] > sizes[2] > sizes[3] > 0 and sizes[5] > 0
