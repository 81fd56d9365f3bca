"""What the operators send to the workers loads where the package can't be imported."""

import subprocess
import sys

import numpy as np
import pytest
from pyspark import cloudpickle
from pyspark.sql import functions as F

from tiersort.llm import ann, common, html_text, quality
from tiersort.llm.common import components, shipped, staged

CODE = """
import pickle
import numpy as np
try:
    import tiersort
    raise SystemExit("the package is here")
except ImportError:
    pass
index, model, page_model, extract = pickle.load(open("sent", "rb"))
cell, codes = index.encode(np.eye(8)[:3])
assert len(cell) == 3 and codes.shape == (3, 4)
assert len(model.evidence("some words of a text")) == 2
assert "word" in extract("<html><body><article><p>A long paragraph with a word, and more of them.</p></article></body></html>", page_model)
"""


def test_models_load_without_the_package(tmp_path):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(300, 8))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    index = ann.Index(x, ann.kmeans(x, 4, rng), 4)
    model = quality.Model(np.ones(quality.MEASURES), np.zeros(quality.MEASURES), np.ones(quality.MEASURES), ["word"], np.ones(4))
    (tmp_path / "sent").write_bytes(cloudpickle.dumps((index, model, html_text.standard_model(), html_text.main_text)))
    done = subprocess.run([sys.executable, "-c", CODE], cwd=tmp_path, capture_output=True, text=True, env={"PATH": "/usr/bin"}, timeout=100)
    assert done.returncode == 0, done.stderr


def test_shipped_objects_come_back(spark):
    get = shipped(spark, {"a": np.arange(3)})
    assert get()["a"].tolist() == [0, 1, 2]


@pytest.mark.parametrize("apart", [0, 1_000_000])
def test_components_with_hubs(spark, monkeypatch, apart):
    monkeypatch.setattr(common, "HUB_TABLE", apart)
    star = spark.range(1, 4000).select(F.lit(0).cast("long").alias("u"), F.col("id").alias("v"))
    chain = spark.range(10_000, 10_040).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))
    got = {r.id: r.component for r in components(staged(star.unionByName(chain), "test")).collect()}
    assert got == {i: 0 for i in range(4000)} | {i: 10_000 for i in range(10_000, 10_041)}
