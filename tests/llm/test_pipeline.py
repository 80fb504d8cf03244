"""The pipeline's stages against their operators, and that a repository without the text operators still imports."""

from __future__ import annotations

import os
import shutil
import subprocess
import sys

from pyspark.sql import functions as F

from pdpview.llm import decontaminate, mixing, quality, registry, setjoin

ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


def test_stages(spark, small):
    import corpus_pipeline as p

    docs = registry.table(spark, small, "documents")
    assert [n for n, _ in p.STAGES] == ["quality rules", "near duplicates", "decontamination", "source mix", "token output"]
    ids = lambda d: sorted(r.doc_id for r in d.select("doc_id").collect())
    now = p.STAGES[0][1](spark, docs, small).cache()
    assert ids(now) == ids(quality.assess(docs).filter("kept")) and now.columns == docs.columns
    nxt = p.STAGES[1][1](spark, now, small).cache()
    assert ids(nxt) == ids(setjoin.join_components(now).filter("doc_id = component_id")) and nxt.columns == docs.columns
    bench = registry.table(spark, small, "benchmark")
    now = p.STAGES[2][1](spark, nxt, small).cache()
    assert ids(now) == ids(decontaminate.contamination(nxt, bench).filter("NOT contaminated")) and now.columns == docs.columns
    nxt = p.STAGES[3][1](spark, now, small).cache()
    words = nxt.agg(F.sum(mixing.word_count(F.col("text")))).first()[0]
    assert words == mixing.mix_words(now).agg(F.sum("taken")).first()[0] and nxt.columns == docs.columns
    out = p.STAGES[4][1](spark, nxt, small)
    assert out.count() == nxt.count()
    again = p.run(spark, small)
    assert sorted(map(tuple, again.collect())) == sorted(map(tuple, out.collect()))


ODD_SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, __h long, tok string, c long, row string, fp long, n int"


def odd_documents(spark):
    """Null and repeated ids, null texts, exact and near copies, a benchmark passage, a very long text, clashing names."""
    clean = lambda k: " ".join(f"{'the of and to in a is that for it'.split()[j % 10]} w{k}x{j}" for j in range(60))
    texts = [None, "", " \n", clean(1), clean(1), clean(1) + " more", clean(2), clean(3), clean(4) + " leaked one two three four five six seven eight nine ten " + clean(5), " ".join(clean(k) for k in range(100, 130)), clean(6), clean(6)]
    ids = [1, 2, 3, 4, 5, 6, None, None, 7, 8, 9, 9]
    rows = [(i, t, None if k % 5 == 0 else "en", [None, "a", "b", ""][k % 4], len(t or ""), k, "t", 3, "r", 4, 5) for k, (i, t) in enumerate(zip(ids, texts, strict=True))]
    return spark.createDataFrame(rows, ODD_SCHEMA).repartition(3)


def test_stages_on_odd_and_empty_tables(spark, tmp_path):
    import corpus_pipeline as p

    bench = spark.createDataFrame([(1, "leaked one two three four five six seven eight nine ten"), (2, None)], "item_id long, text string")
    bench.write.parquet(str(tmp_path / "benchmark.parquet"))
    odd = odd_documents(spark)
    texts = {r.text for r in odd.collect()}
    now, kept = odd, []
    for _, stage in p.STAGES[:-1]:
        now = stage(spark, now, str(tmp_path)).cache()
        assert now.columns == odd.columns
        kept.append(now.collect())
    words = lambda r: len((r.text or "").split())
    assert {r.text for r in kept[0]} == {t for t in texts if len((t or "").split()) >= 50} and len(kept[0]) == 9
    # a copy and a near copy go, and one of two equal rows; texts under null ids stay
    assert sorted((r.doc_id is not None, r.doc_id or 0) for r in kept[1]) == [(False, 0), (False, 0), (True, 4), (True, 7), (True, 8), (True, 9)]
    assert {r.text for r in kept[2]} == {r.text for r in kept[1] if "leaked" not in r.text} and len(kept[2]) == 5
    assert sum(map(words, kept[3])) > 0 and all(words(r) for r in kept[3])
    tokens = p.STAGES[-1][1](spark, now, str(tmp_path)).collect()
    assert len(tokens) == len(kept[3]) and sum(r.n_tokens for r in tokens) > sum(map(words, kept[3]))
    empty = odd.limit(0)
    for _, stage in p.STAGES[:-1]:
        empty = stage(spark, empty, str(tmp_path))
        assert empty.columns == odd.columns and empty.count() == 0
    assert p.STAGES[-1][1](spark, empty, str(tmp_path)).count() == 0


def test_repository_without_text_operators(tmp_path):
    """The rest of the repository works when the text operators' folders are gone, with or without the pipeline's file."""
    shutil.copytree(ROOT, tmp_path / "r", ignore=shutil.ignore_patterns(".git", "__pycache__"))
    for x in ("pdpview/llm", "tests/llm"):
        shutil.rmtree(tmp_path / "r" / x)
    code = "import __spark_entry__ as e; q = e.queries(); assert len(q) > 100 and not any(n.startswith('op') and n[2].isdigit() or n == 'pipeline' for n in q)"
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    run = lambda *c: subprocess.run([sys.executable, "-B", *c], cwd=tmp_path / "r", check=True, env=env)
    run("-c", code)
    os.remove(tmp_path / "r" / "corpus_pipeline.py")
    run("-c", code)
    run("-m", "pytest", "-x", "-q", "-p", "no:cacheprovider", "tests/test_methods.py", "-k", "shares or noise or transcript or padding or empty")
    (tmp_path / "r" / "corpus_pipeline.py").write_text("import a_library_that_is_not_there\n")
    broken = subprocess.run([sys.executable, "-B", "-c", code], cwd=tmp_path / "r", env=env, capture_output=True, text=True)
    assert "a_library_that_is_not_there" in broken.stderr  # a missing dependency is not taken for a missing folder
