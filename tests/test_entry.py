"""The driver's contract, and plans at scale: what is read and what is shuffled."""

import shutil
import subprocess
import sys
from pathlib import Path

import numpy as np
import pytest

import __spark_entry__
from pyspark.sql import functions as F

from annspark import catalog
from annspark.operators import exact, kmeans, metrics, scoring, select, transform
from annspark.operators.activation import activated_bits
from annspark.params import Params
from annspark.plans import index as indexes
from annspark.plans import search
from annspark.sources.vectors import fixture

SF = "/root/testdata/sf0.001"


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_contract(spark):
    queries, oracles = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(oracles) <= set(queries) and len(queries) >= 89
    assert __spark_entry__.entry(spark).columns == ["qid", "rank", "vec_id", "dist"]


@pytest.mark.parametrize("gone", [("annspark/llm", "tests/llm"), ("annspark/llm", "tests/llm", "corpus_pipeline.py"), ("corpus_pipeline.py",)])
def test_contract_without_the_training_data_operators(tmp_path, gone):
    """The engine's queries import and are all there when the optional folders are deleted."""
    root = Path(__spark_entry__.__file__).parent
    shutil.copytree(root, tmp_path / "copy", ignore=shutil.ignore_patterns(".git", "__pycache__", *gone, *(Path(g).name for g in gone)))
    code = "import __spark_entry__ as e; from annspark import catalog; q = e.queries(); assert set(e.oracle_sql()) <= set(q) and set(catalog.queries()) <= set(q); print(len(catalog.queries()), 'pipeline' in q)"
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "copy", capture_output=True, text=True, timeout=120, check=False)
    assert done.stdout.split() == [str(len(catalog.queries())), "False"], done.stderr[-2000:]


def test_plans(spark):
    base, queries = fixture(spark, SF, "embeddings")
    p = Params(ns=4, s=4, cells=16, t=1, space="agnostic")
    index = indexes.create(base, p)
    qids, q = next(exact.query_blocks(queries))
    scorer = scoring.bit_scorer(qids, q, activated_bits(queries, index.space, index.books, index.counts, p.alpha), 4, 4)
    hist = select.histogram(index.points, scorer, 4)
    # the histogram reads codes only, and shuffles counts
    text = plan(hist)
    assert "embedding" not in text.split("ReadSchema")[1].split("\n")[0] and text.count("Exchange") == 1
    choice = select.by_cutoff(select.counts_of(hist, qids, 4), p.beta, index.n, "lookahead")
    assert "Exchange" not in plan(search.refine(index.points, scorer, choice, 10))
    # the hold-out reaches the scan; the top-k prunes before its shuffle
    assert "PushedFilters" in plan(base) and "WindowGroupLimit" in plan(exact.knn(base, queries, 3))


def test_cost_and_cross_check(spark):
    base, _ = fixture(spark, SF, "embeddings")
    cost = metrics.spark_cost(spark, lambda: base.groupBy(F.col("vec_id") % 3).count().collect())
    assert cost["tasks"] >= 1 and cost["shuffle_write_bytes"] > 0
    space = transform.fit(base, Params(ns=2, s=4, space="agnostic"))
    ours, theirs = kmeans.fit_all(base, space, 4, 8), kmeans.fit_mllib(base, space, 4, 8)
    rows = np.array([r[0] for r in base.select("embedding").collect()])

    def loss(books):
        return sum(((p[:, None] - b) ** 2).sum(axis=2).min(axis=1).sum() for p, b in zip(kmeans.half_parts(space, rows), books))

    assert 0.9 < loss(ours) / loss(theirs) < 1.1
