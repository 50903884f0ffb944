"""The pipeline's stages against plain Python, and the queries against their SQL."""

import duckdb
import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")

from lookalike.llm import langid  # noqa: E402
from lookalike.llm import queries as Q  # noqa: E402
from test_dedup import brute_near  # noqa: E402


def table(spark, sf, name="documents"):
    return spark.read.parquet(f"{sf}/{name}.parquet")


def test_stages_against_brute_force(spark, sf):
    docs = table(spark, sf)
    now = docs
    seen = {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        nxt = stage(spark, now, sf)
        assert nxt.columns == docs.columns
        seen[name] = (now.collect(), nxt.collect())
        path = f"/tmp/lookalike-pipeline-{name}"
        nxt.write.mode("overwrite").parquet(path)
        now = spark.read.parquet(path)
    before, after = seen["language_id"]
    model = tuple(sorted(langid.fit(docs.filter(~langid.held_out_expr("doc_id"))).items()))
    assert sorted(r["doc_id"] for r in after) == sorted(r["doc_id"] for r in before if not langid.decide(r["text"], model)[3])
    before, after = seen["exact_dedup"]
    first = {}
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    for r in sorted(before, key=lambda r: r["doc_id"]):
        first.setdefault((r["text"] or "").translate(low), r["doc_id"])
    assert sorted(r["doc_id"] for r in after) == sorted(first.values())
    before, after = seen["minhash_near_dedup"]
    want = brute_near([(r["doc_id"], r["text"]) for r in before], 80)
    assert sorted(r["doc_id"] for r in after) == sorted(i for i, w in want.items() if w[2])
    before, after = seen["substring_dedup"]
    assert sorted(r["doc_id"] for r in before) == sorted(r["doc_id"] for r in after)
    texts = {r["doc_id"]: r["text"] for r in before}
    windows = {}
    for r in sorted(after, key=lambda r: r["doc_id"]):
        assert r["n_chars"] == len(r["text"] or "")
        assert len(r["text"] or "") <= len(texts[r["doc_id"]] or "")
        w = (r["text"] or "").split()
        for i in range(len(w) - 59):
            s = tuple(w[i : i + 60])
            if len(set(s)) > 20:
                assert windows.setdefault(s, r["doc_id"]) == r["doc_id"], "a passage of 60 words is left in two documents"
    pieces = corpus_pipeline.pack(spark, now, sf).collect()
    assert {r["doc_id"] for r in pieces} == {r["doc_id"] for r in after}


def test_run(spark, sf):
    assert corpus_pipeline.run(spark, sf).count() > 0


@pytest.mark.parametrize("name", sorted(Q.oracle_sql()))
def test_queries_equal_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "pages", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    want = con.execute(Q.oracle_sql()[name])
    cols = sorted(d[0] for d in want.description)
    got = Q.queries()[name](spark, sf)
    assert sorted(got.columns) == cols
    names = [d[0] for d in want.description]
    a = sorted(str([dict(zip(names, r))[c] for c in cols]) for r in want.fetchall())
    b = sorted(str([r[c] for c in cols]) for r in got.collect())
    assert a == b


ODD = "doc_id long, text string, lang string, source string, n_chars long, kept boolean, h128 string, __id long, marked_id long, n_chunks long"


def test_stages_on_odd_rows(spark, sf, tmp_path):
    """Nulls in any column, empty and very long texts, repeated rows and clashing extra columns pass every stage."""
    en, de = "the cat and the dog went to the house of the man ", "der hund und die katze gingen zum haus von dem mann "
    rows = [(i, f"{en}{i} word{i} and word{i * 7} ", "en", "s") for i in range(40)] + [(100 + i, f"{de}{i} wort{i} und wort{i * 7} ", "de", None) for i in range(40)]
    rows += [(200, None, "en", "s"), (201, "", "de", "s"), (202, "12 !!", None, "s"), (None, en * 3, None, None), (203, en * 20000, "en", "s"), (204, en * 20000, "en", "s"), (5, rows[5][1], "en", "s"), (300, rows[3][1].upper(), None, "s")]
    df = spark.createDataFrame([(*r, None, None, "x", 7, 8, None) for r in rows], ODD)
    now, kept = df, {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, now, sf)
        assert out.columns == df.columns
        path = str(tmp_path / name)
        out.write.parquet(path)
        now = spark.read.parquet(path)
        kept[name] = [r["doc_id"] for r in now.select("doc_id").collect()]
    assert not {200, 201, 202} & set(kept["language_id"]) and None in kept["language_id"] and 203 in kept["language_id"]
    assert 300 not in kept["exact_dedup"] and 204 not in kept["exact_dedup"] and None in kept["exact_dedup"]
    assert set(kept["substring_dedup"]) == set(kept["minhash_near_dedup"]) and None in kept["substring_dedup"]
    pieces = corpus_pipeline.pack(spark, now, sf).collect()
    assert {r["doc_id"] for r in pieces} == set(kept["substring_dedup"])


def test_stages_on_an_empty_table(spark, sf):
    now = table(spark, sf).limit(0)
    for _, stage in corpus_pipeline.STAGES:
        now = stage(spark, now, sf)
        assert now.count() == 0
