"""Operators that once returned less than the whole job."""

import duckdb

from lookalike.operators import graph
from lookalike.plans import method_queries, operator_queries  # noqa: F401
from lookalike.plans.registry import QUERIES
from lookalike.sources import workloads

_TFIDF = r"""WITH t AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[a-zà-ÿ]+')) AS w FROM '{sf}/documents.parquet'),
tf AS (SELECT doc_id, w, count(*) AS n FROM t GROUP BY ALL), df AS (SELECT w, count(*) AS d FROM tf GROUP BY w)
SELECT doc_id, w, n * ln((1.0 + (SELECT count(*) FROM '{sf}/documents.parquet')) / (1 + d)) FROM tf JOIN df USING (w)"""


def test_tfidf_keeps_rare_terms(spark, sf):
    want = {(d, w): v for d, w, v in duckdb.sql(_TFIDF.format(sf=sf)).fetchall()}
    rows = QUERIES["tfidf_terms"](spark, sf).collect()
    got = {(r.doc_id, r.w): r.tfidf for r in rows}
    assert len(rows) == len(got) and got.keys() == want.keys()
    assert all(abs(got[k] - want[k]) < 2e-6 for k in want)


def test_edges_page_keeps_common_targets(spark, tmp_path):
    rows = [(i, "u", '<html lang="en"><a href="/all">' + (f'<a href="/p{i // 2}">' if i < 20 else "")) for i in range(230)]
    spark.createDataFrame(rows, "page_id long, url string, html string").write.parquet(str(tmp_path / "pages.parquet"))
    got = {(r.src, r.dst): r.support for r in QUERIES["edges_page"](spark, str(tmp_path)).collect()}
    assert len(got) == 230 * 229 // 2
    assert all(n == (2 if b < 20 and a // 2 == b // 2 else 1) for (a, b), n in got.items())
    assert workloads.page_graph(spark, str(tmp_path)).edges.count() == len(got)


def test_blocks_of_a_group_make_each_pair_once(spark):
    rows = spark.createDataFrame([(g, i) for g, n in ((1, 40), (2, 3), (3, 1)) for i in range(n)], "g int, i long")
    whole = sorted(map(tuple, graph.co_occurrence(rows, "g", "i").collect()))
    assert sorted(map(tuple, graph.co_occurrence(rows, "g", "i", block=7).collect())) == whole and len(whole) == 780


def test_near_copy_edges_equal_brute_force(spark, tmp_path):
    common = [f"c{i}" for i in range(30)]
    texts = [None, "", "  ", "a b c", "c  b a", "a b c d", "x", "X ", " y x"]
    for k in range(12):  # near copies that only rare words tell apart, or hold together
        texts += [" ".join([*common, *[f"r{k}_{j}" for j in range(n)]]) for n in (3, 9)] + [" ".join(f"q{k // 3}_{j}" for j in range(20 + k % 3 * 2))]
    rows = list(enumerate(texts))
    spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars int").write.parquet(str(tmp_path / "documents.parquet"))
    sets = {i: set(t.lower().split()) for i, t in rows if t and t.split()}
    want = {(a, b) for a in sets for b in sets if a < b and 5 * len(sets[a] & sets[b]) > 4 * len(sets[a] | sets[b])}
    got = [tuple(r) for r in QUERIES["near_copy_edges"](spark, str(tmp_path)).collect()]
    assert set(got) == want and len(got) == len(want) and {(3, 4), (6, 7)} <= want
