"""Size of the language model, and what it rejects."""

import base64
import random

import numpy as np
import pytest

from conftest import DATA
from heavyhitters.llm import language_id

IDEOGRAPHS = [chr(0x4E00 + i) for i in range(3000)]


def words(rng, alphabet, n):
    return " ".join("".join(rng.choice(alphabet) for _ in range(rng.randint(2, 9))) for _ in range(n))


@pytest.fixture(scope="module")
def model(spark):
    return language_id.fit(spark.read.parquet(f"{DATA}/documents.parquet"))


def test_long_texts_of_a_large_script(model):
    rng = random.Random(1)
    assert model.matrix.shape[1] >= 8192 and language_id.FIT_ROWS >= 6000
    assert model.predict([words(rng, IDEOGRAPHS, 500) for _ in range(50)])[2].mean() > 0.9


def test_packed_clusters_are_those_of_dense_rows():
    rng = np.random.default_rng(2)
    x = np.where(rng.random((300, language_id.BUCKETS)) < 0.01, rng.random((300, language_id.BUCKETS)), 0).astype(np.float32)
    x[:150, :40] += 1
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    split = [language_id._pack(x[at : at + 128]) for at in range(0, 300, 128)]
    assert all((b.dense() == x[at : at + 128]).all() for at, b in zip(range(0, 300, 128), split))
    c = language_id._cluster(split, 3)
    own = (x @ c.T).argmax(axis=1)
    for j in set(own):
        centre = x[own == j].sum(axis=0)
        assert c[j] @ centre / np.linalg.norm(centre) > 0.98


@pytest.mark.parametrize("n", [20, 200, 500])
def test_unknown_texts_are_rejected(model, n):
    rng = random.Random(3)
    unseen = [words(rng, alphabet, n) for alphabet in (IDEOGRAPHS, "абвгдежзиклмнопрст", "bcdfghjklmnpqrstvwxz") for _ in range(30)]
    encoded = [base64.b64encode(rng.randbytes(4 * n)).decode() for _ in range(30)]
    for part in (unseen[:30], unseen[30:60], unseen[60:], encoded):
        assert model.predict(part)[2].mean() >= 0.9


def test_known_texts_are_kept(spark, model):
    """Documents of another table than the fitted one, and their beginnings."""
    texts = [r.text for r in spark.read.parquet(f"{DATA.replace('0.001', '0.01')}/documents.parquet").collect() if any(map(str.isalpha, r.text or ""))]
    assert model.predict(texts)[2].mean() < 0.01
    assert model.predict([" ".join(t.split()[:12]) for t in texts])[2].mean() < 0.02
