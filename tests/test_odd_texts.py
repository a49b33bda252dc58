"""Queries against their SQL on built tables of odd texts."""

import duckdb
from oracle import compare

from corpuskit import registry
from corpuskit.plans import encode, search
from corpuskit.workloads import checks, vectors


def _beside(spark, sf_dir, out, **made):
    """A folder with the smoke tables, of which some are replaced by rows of (key, text)."""
    for name in ("orders", "customer", "labels"):
        spark.read.parquet(f"{sf_dir}/{name}.parquet").write.parquet(f"{out}/{name}.parquet")
    for name, texts in made.items():
        key = "item_id long" if name == "benchmark" else "doc_id long"
        rows = [(k, t, "en", "s", len(t or "")) for k, t in enumerate(texts)]
        spark.createDataFrame(rows, f"{key}, text string, lang string, source string, n_chars long").coalesce(1).write.parquet(f"{out}/{name}.parquet")
    con = duckdb.connect()
    for name in ("orders", "customer", "labels", *made):
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM read_parquet('{out}/{name}.parquet/*.parquet')")
    return str(out), con


def test_free_text_search_ranks_titles_that_cancel_out_as_in_sql(spark, sf_dir, tmp_path, monkeypatch):
    """Titles and queries without a direction, pairs that meet nowhere, null queries, capitals with two small forms; both forms of the search."""
    enc = encode.HashingEncoder(256)
    against = lambda p: [w for w in (f"w{i}" for i in range(20_000)) if enc._place(w) == (enc._place(p)[0], -enc._place(p)[1])]
    titles, asked = against("passage"), against("query")
    texts = [titles[0], titles[1], "the house", "a tree", f"{titles[2]} hill", "ΟΔΟΣ one", "İzmir", "!", "", *["house and tree"] * 3]
    questions = ["house", asked[0], "passage", titles[3], None, "", "tree and hill", "οδοσ", "izmir", f"house {titles[4]}"]
    out, con = _beside(spark, sf_dir, tmp_path / "t", documents=texts, benchmark=questions)
    oracle = registry.oracle_sql()["recommend_by_text"]
    found = vectors.recommend_by_text(spark, out)
    assert compare(found, con, oracle) is None
    assert found.filter("isnan(score) and rank = 1").count() > 1
    monkeypatch.setattr(search, "is_small", lambda df: False)
    assert compare(vectors.recommend_by_text(spark, out), con, oracle) is None


def test_summary_of_odd_texts_is_that_of_the_sql(spark, sf_dir, tmp_path):
    """Words that cancel out at 16 places, vertical tabs, replacement characters and texts without a word."""
    enc = encode.HashingEncoder(16)
    at, sign = enc._place("passage")
    against = [w for w in (f"w{i}" for i in range(2_000)) if enc._place(w) == (at, -sign)]
    en = "the cat and the dog in that house with the garden is for the children of the town"
    texts = [*against[:3], "\v", "\v\v a b", "\v".join(f"{en} {en}".split()), f"{en}{chr(11) * 70} {en}", f"{en} {en} �", "�" * 40 + en * 2, "", " \n", "!", None, f"{en}. " * 12]
    out, con = _beside(spark, sf_dir, tmp_path / "t", documents=texts)
    assert compare(checks.validation_summary(spark, out), con, registry.oracle_sql()["validation_summary"]) is None
