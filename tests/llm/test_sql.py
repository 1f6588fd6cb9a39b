"""Queries of this subpackage against their SQL in DuckDB, on the smallest tables and on odd rows."""

import os

import duckdb
import pytest

from slidemedian.llm import queries

DATA = "/root/testdata/sf0.001"


def compare(spark, key, folder, out):
    queries.QUERIES[key](spark, folder).write.parquet(out)
    duck = duckdb.connect()
    for name in os.listdir(folder):
        files = f"{folder}/{name}/*.parquet" if os.path.isdir(f"{folder}/{name}") else f"{folder}/{name}"
        duck.execute(f"CREATE VIEW {name.split('.')[0]} AS SELECT * FROM '{files}'")
    duck.execute(f"CREATE TABLE wanted AS {queries.ORACLE_SQL[key]}")
    duck.execute(f"CREATE TABLE given AS SELECT * FROM '{out}/*.parquet'")
    kinds = [{r[0]: r[1] for r in duck.execute(f"DESCRIBE {t}").fetchall()} for t in ("wanted", "given")]
    assert kinds[0] == kinds[1]
    columns = ", ".join(f'"{c}"' for c in sorted(kinds[0]))
    for one, other in (("wanted", "given"), ("given", "wanted")):
        assert duck.execute(f"SELECT {columns} FROM {one} EXCEPT ALL SELECT {columns} FROM {other} LIMIT 5").fetchall() == []
    return duck.execute("SELECT count(*) FROM given").fetchone()[0]


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
@pytest.mark.parametrize("key", queries.ORACLE_SQL)
def test_query_equals_its_sql(spark, key, tmp_path):
    assert compare(spark, key, DATA, str(tmp_path / "out")) > 0


def test_odd_documents(spark, tmp_path):
    texts = [None, "", " \t\n", "One", "one", "ONE two", "one\x0btwo", "é è", "É è", "a b c d e f g h i j k l", "a b c d e f g h i j k z", "a b  c d e f g h i j k l", "x\u00a0y z", "数 学 " * 40]
    rows = [(i, t, "clash", i % 2 == 0) for i, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, component_id string, kept boolean").write.parquet(str(tmp_path / "in" / "documents.parquet"))
    for key in ("op1_near_dedup", "op6_exact_dedup"):
        assert compare(spark, key, str(tmp_path / "in"), str(tmp_path / key)) == len(texts)


def test_odd_pages(spark, tmp_path):
    hosts = ["shop.Example.ORG", "example.org", "a.b.fr.com", "com", "notcom", "x.net", "y.x.net", "blog.x.net", "bad.com", "sub.bad.com", ""]
    paths = ["/es/1", "/en/1x", "/en/2", "/fr/1?de=/de/", "/de/1", "", "?q", "#/de/", "/fr/"]
    rows = [(i, f"http://{h}{p}", f"<a href='https://{hosts[i % 7]}/x'>") for i, (h, p) in enumerate((h, p) for h in hosts for p in paths)]
    rows += [(900, None, None), (901, "no scheme/de/", ""), (902, "ftp://com/de/", None), (903, "a://b://com/de/", None), (904, "http://com\n/de/", "<a href=//bad.com>")]
    spark.createDataFrame([(*r, "clash", "x") for r in rows], "page_id long, url string, html string, host string, trust string").write.parquet(str(tmp_path / "in" / "pages.parquet"))
    assert compare(spark, "op8_url_filter", str(tmp_path / "in"), str(tmp_path / "out")) == len(rows)


def test_odd_vectors(spark, tmp_path):
    rows = [(0, [1.0, 0.0]), (1, [2.0, 0.1]), (2, [1.0, 0.0, 0.0]), (3, None), (4, []), (5, [0.0, 0.0]), (6, [None, 1.0]), (7, [float("inf"), 1.0]), (8, [-1.0, 0.0]), (9, [1.0, 0.0]), (10, [3.0]), (11, [5.0])]
    spark.createDataFrame([(*r, "clash", 7) for r in rows], "vec_id long, embedding array<float>, component_id string, n_links int").write.parquet(str(tmp_path / "in" / "embeddings.parquet"))
    assert compare(spark, "op5_embedding_dedup", str(tmp_path / "in"), str(tmp_path / "out")) == len(rows)
