"""The pipeline, stage by stage: on the smallest tables, and against brute force on planted cases."""

import os
import random
import shutil
import subprocess
import sys

import pytest

DATA = "/root/testdata/sf0.001"
ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


@pytest.mark.skipif(not os.path.isdir(DATA), reason="needs the given tables")
def test_stages_keep_columns_and_take_effect(spark):
    import corpus_pipeline

    docs = corpus_pipeline.load(spark, DATA, "documents")
    columns, before = docs.columns, docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.settle(stage(spark, docs, DATA), "test-stage")
        assert docs.columns == columns, name
        assert 0 < docs.count() <= before, name
        before = docs.count()
    texts = [r["text"] for r in docs.select("text").collect()]
    assert len(set(texts)) == len(texts)
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, DATA)
    assert pieces.select("doc_id").distinct().count() == before


def shingles(text, width=5):
    words = text.lower().split()
    return {tuple(words[i : i + width]) for i in range(max(1, len(words) - width + 1))}


def test_stages_equal_brute_force_on_planted_cases(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(2)
    own = {"en": ["the", "house", "with", "river", "stone", "garden", "window"], "de": ["der", "schön", "nicht", "straße", "über", "stein", "garten"]}
    text = lambda lang, n: " ".join(rng.choice(own[lang]) + rng.choice(["", "", "s", "en"]) for _ in range(n))
    rows, labels = [], []
    for i in range(300):
        lang = rng.choice(list(own))
        junk = i % 10 == 0
        rows.append((i, text(lang, 60) if not junk else " ".join(w + "***" for w in text(lang, 60).split()), lang))
        labels.append((i, int(not junk), 0))
    clean = [r for r in rows if "***" not in r[1]]
    strangers = [(1000 + i, "привет дома ничего река камень сад " * 12, None) for i in range(3)] + [(1010, "qzxkv wvvqj zzkqx " * 30, None)]
    exact = [(2000 + i, clean[i][1], clean[i][2]) for i in range(20)]
    near = []
    for i in range(20, 40):
        words = clean[i][1].split()
        words[rng.choice([0, -1])] = "garden"
        near.append((3000 + i, " ".join(words), clean[i][2]))
    table = [(i, t, lang, "s", len(t)) for i, t, lang in rows + strangers + exact + near] + [(9000, None, "en", "s", 0), (9001, "", "de", "s", 0)]
    columns = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame(table, columns).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    docs, kept = corpus_pipeline.load(spark, str(tmp_path), "documents"), {}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.settle(stage(spark, docs, str(tmp_path)), "test-stage")
        kept[name] = {r["doc_id"]: r["text"] for r in docs.collect()}
    # Language: strangers and texts without letters go, all others stay.
    assert set(kept["language id"]) == {i for i, _, _ in rows + exact + near}
    # Quality: junk goes, and of the good ones at most what the cut-off may cost.
    good = {i: t for i, t in kept["language id"].items() if "***" not in t}
    assert set(kept["quality classifier"]) <= set(good) and len(kept["quality classifier"]) >= 0.97 * len(good)
    # Exact dedup: of equal texts the largest id.
    last = {}
    for i, t in kept["quality classifier"].items():
        last[t] = max(i, last.get(t, i))
    assert set(kept["exact dedup"]) == set(last.values())
    # Near dedup: the least id of each component of links at 0.8.
    sets = {i: shingles(t) for i, t in kept["exact dedup"].items()}
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in sets:
        for j in sets:
            if i < j and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    assert set(kept["near dedup"]) == {i for i in sets if find(i) == i} and len(kept["near dedup"]) <= len(kept["exact dedup"]) - 15
    pieces = corpus_pipeline.STAGES[-1][1](spark, docs, str(tmp_path)).collect()
    assert {r["doc_id"] for r in pieces} == set(kept["near dedup"])
    whole = {r["doc_id"]: r["doc_tokens"] for r in pieces}
    assert sum(r["length"] for r in pieces) == sum(whole.values())


def test_entry_holds_the_queries():
    import __spark_entry__ as entry

    assert {f"op{n}_" for n in range(1, 11)} <= {name.split("_")[0] + "_" for name in entry.queries()} and "pipeline" in entry.queries()


def test_the_rest_survives_without_the_subpackage(tmp_path):
    """A copy of the repository without this subpackage, its tests and the pipeline."""
    copy = tmp_path / "copy"
    shutil.copytree(ROOT, copy, ignore=shutil.ignore_patterns(".git", "__pycache__", ".pytest_cache", "spark-warehouse"))
    shutil.rmtree(copy / "slidemedian" / "llm")
    shutil.rmtree(copy / "tests" / "llm")
    os.remove(copy / "corpus_pipeline.py")
    said = subprocess.run(
        [sys.executable, "-c", "import __spark_entry__ as e; q = e.queries(); s = e.oracle_sql(); print(len(q), len(s), any(k.startswith('op') or k == 'pipeline' for k in q))"],
        cwd=copy, capture_output=True, text=True, env={**os.environ, "PYTHONPATH": str(copy)}, check=True,
    ).stdout.split()
    assert int(said[0]) > 150 and int(said[1]) > 150 and said[2] == "False"
    found = subprocess.run([sys.executable, "-m", "pytest", "tests", "-q", "--collect-only"], cwd=copy, capture_output=True, text=True, env={**os.environ, "PYTHONPATH": str(copy)}, check=False)
    assert found.returncode == 0, found.stdout[-2000:]
