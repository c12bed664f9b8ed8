"""Language of very long texts: held-out texts of one language joined to lengths up to some MB."""

import sys
from pathlib import Path

import numpy as np
import pytest

sys.path.insert(0, str(Path(__file__).parents[1]))
from conftest import DATA  # noqa: E402

from gaptide.llm import langid, queries  # noqa: E402


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet")


def test_language_accuracy_by_length(spark, docs):
    model = langid.learn(docs, ~queries.held_out())
    held = docs.where(queries.held_out()).where("lang is not null and text is not null").select("lang", "text").collect()
    whole = {x: "\n".join(r["text"] for r in held if r["lang"] == x) for x in sorted({r["lang"] for r in held})}
    assert len(whole) >= 3
    sizes = (1_000, 10_000, 100_000, 300_000, 1_000_000, 3_000_000)
    rows = [(x, n, (t * (n // len(t) + 1))[:n]) for x, t in whole.items() for n in sizes]
    got = langid.predict(spark.createDataFrame(rows, "lang string, n long, text string").repartition(4), model).collect()
    assert [(r["lang"], r["n"], r["lang_pred"]) for r in got if r["lang_pred"] != r["lang"]] == []


def test_places_never_fill_and_no_byte_is_skipped():
    gen = np.random.default_rng(1)
    pool = ["".join(gen.choice(list("abcdefghijklm"), 5)) for _ in range(120)]
    long = np.frombuffer(" ".join(gen.choice(pool, 100_000)).encode(), np.uint8)
    raw = np.concatenate((long, long[:100]))
    p = langid.spectrum(raw, np.array([0, len(long), len(raw)]))
    assert np.allclose(p[1], langid.unit(langid.presence(raw, [len(long)], [len(raw)]))[0])
    assert (langid.presence(raw, [0], [langid.STRETCH]) > 0).mean() < 0.6
    for at in (0, 2047, 2048, 500_001, len(long) - 1):  # bytes that are nowhere else change the whole text's row
        other = long.copy()
        other[max(0, at - 3) : at + 1] = [7, 1, 2, 3][-min(4, at + 1) :]
        assert not np.array_equal(langid.spectrum(other, np.array([0, len(other)]))[0], p[0])
