"""URL filter and source mixing against plain Python, the plans being free of Python workers."""

import hashlib

import pytest
from pyspark.sql import functions as F

from sparse_neighbors.llm import mixing, queries, url_filter

RULES = queries.URL_RULES


def judge(url):
    rest = url.split("://", 1)[1] if url and "://" in url else ""
    at = min((rest.index(c) for c in "/?#" if c in rest), default=len(rest))
    host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in rest[:at])
    tail = rest[at:]
    path = tail[: min((tail.index(c) for c in "?#" if c in tail), default=len(tail))]
    best = None
    for r in RULES:
        own, prefix = r.key[: r.key.index("/")], r.path
        if (host == own or host.endswith("." + own)) and path.startswith(prefix) and (best is None or len(r.key) > len(best.key)):
            best = r
    return host, path, best and best.key, best.verdict if best else "allow"


URLS = [
    None, "", "no scheme/en/", "http://a.com/en/1", "https://Example.COM/en/7x", "https://www.example.com/en/8", "http://x.example.net/de/8/9", "http://example.net/de/7", "http://net/de/", "http://b.org/es/",
    "http://b.org/es", "http://com?q=/en/", "http://com#x", "http://notexample.com/en/7", "http://a.com:80/en/1", "ftp://u@x.org/es/?a://b", "http://..com/en/", "http:///en/", "http://com/en/://x", "http://a.com/EN/1", "http://a.com/en/7\nb",
]


def test_verdicts_equal_plain_python(spark):
    pages = spark.createDataFrame([(i, u, "h", "r") for i, u in enumerate(URLS)] + [(None, "http://a.com/en/", "h", "r"), (1, "", "h", "r")], "page_id long, url string, host string, rule string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filter.judge_urls(pages, RULES).collect()}
    assert {i: got[i] for i in range(len(URLS))} == {i: judge(u) for i, u in enumerate(URLS)}
    assert got[None][2] == "com/en/"
    assert url_filter.judge_urls(pages.where("false"), RULES).count() == 0


def test_cascade_is_exact(spark):
    universe = spark.range(20_000).select(F.concat(F.lit("k"), "id").alias("key"))
    listed = universe.where("hash(key) % 17 = 0")
    levels = url_filter.build_cascade(listed, universe)
    assert len(levels) > 2
    member = url_filter.is_listed(F.col("key"), levels)
    assert universe.where(member).exceptAll(listed).count() == 0 and listed.where(~member).count() == 0
    assert url_filter.build_cascade(listed.where("false"), universe) == []


def fill(sizes, weights, share, most):
    """Targets by dealing the excess again until none is above."""
    names = [*sorted(n for n in sizes if n is not None), *([None] if None in sizes else [])]
    weight = {n: weights[i % len(weights)] for i, n in enumerate(names)}
    budget, target, open_ = share * sum(sizes.values()), {}, set(names)
    while open_:
        level = (budget - sum(target.values())) / sum(weight[n] for n in open_)
        over = [n for n in open_ if level * weight[n] > most * sizes[n]]
        target |= {n: most * sizes[n] for n in over} or {n: level * weight[n] for n in open_}
        open_ -= set(over or open_)
    return target


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, "w " * (i % 40), f"s{i * i % 7}" if i % 11 else None, 1) for i in range(600)] + [(None, "a b", "é", 2), (607, None, "empty", 3), (8, "x\x0by\u00a0z", "s1", 4), (8, "x y z", "s1", 4)]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, size int")


def test_targets_and_draws(docs):
    got = mixing.mix_plan(docs).toPandas()
    plain = docs.toPandas()
    plain["words"] = plain.text.fillna("").map(lambda t: len([w for w in __import__("re").split(r"[\x20\x09-\x0D]+", t) if w]))
    sizes = {n: int(plain[plain.source.isna() if n is None else plain.source == n].words.sum()) for n in [*plain.source.dropna().unique(), None]}
    want = fill(sizes, (5, 2, 1), 1.5, 2)
    by_id = {(None if i != i else int(i)): n for i, n in zip(plain.doc_id, plain.source, strict=True)}
    for r in got.itertuples():
        doc_id = None if r.doc_id != r.doc_id else int(r.doc_id)
        source = by_id[doc_id]
        assert r.source_size == sizes[source] and abs(r.target - want[source]) < 1e-6 * max(1, r.target)
        rate = r.target / r.source_size if r.source_size else 0
        draw = int(hashlib.md5(f"{'' if doc_id is None else doc_id}:mix".encode()).hexdigest()[:13], 16) / 2**52
        assert r.taken == r.size * (int(rate) + (draw < rate - int(rate))) <= 2 * r.size
    assert mixing.mix_plan(docs.where("false")).count() == 0


def test_documents_come_as_often_as_planned(docs):
    plan = mixing.mix_plan(docs).agg(F.sum("taken")).first()[0]
    out = mixing.mix_documents(docs)
    assert out.columns == docs.columns
    assert out.select(F.sum(mixing.word_count(F.col("text")))).first()[0] == plan


@pytest.mark.parametrize("name", ["op9_url_filter", "op10_source_mixing"])
def test_native_plans(spark, data, name):
    text = queries.QUERIES[name](spark, data)._jdf.queryExecution().toString()
    assert not any(x in text for x in ("Python", "Pandas", "Arrow", "Cartesian", "NestedLoop"))
