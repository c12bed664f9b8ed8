"""Secrets of any length and with any symbols are proposed and redacted whole."""

import random
import string
import sys
from pathlib import Path

import numpy as np
import pytest

sys.path.insert(0, str(Path(__file__).parents[1]))
from gaptide.llm import secrets  # noqa: E402

BASE64 = string.ascii_letters + string.digits + "+/"


@pytest.fixture(scope="module")
def forest():
    return secrets.train()


def test_long_values_are_redacted_whole(spark, forest):
    r = random.Random(4)
    values = [(n, form, "".join(r.choice(BASE64) for _ in range(n))) for n in (200, 256, 257, 400, 4000) for form in ('token = "%s" it', "see %s there", "password: %s\nand")]
    texts = [(i, f"some words {form % v} are here") for i, (_, form, v) in enumerate(values)]
    frame = spark.createDataFrame(texts, "doc_id long, text string")
    found = {(r["doc_id"], r["value"]) for r in secrets.scan(frame, forest).collect() if r["is_secret"]}
    assert found == {(i, v) for i, (_, _, v) in enumerate(values)}
    clean = {r["doc_id"]: r["text"] for r in secrets.redact(frame, forest).collect()}
    assert clean == {i: f"some words {form % '[secret]'} are here" for i, (_, form, _) in enumerate(values)}


def test_symbols_before_the_first_digit():
    r = random.Random(5)
    values = ["".join(r.choice(BASE64) for _ in range(40)) for _ in range(2000)]
    values = [v for v in values if any(c.isdigit() for c in v)]
    assert len(values) > 1900 and all(secrets.proposals(f"see {v} here") == [(4, 44, "opaque")] for v in values)


def test_refused_long_value_hides_no_secret_within(forest):
    r = random.Random(6)
    key = "AKIA" + "".join(r.choice(string.ascii_uppercase + string.digits) for _ in range(16))
    text = "key:" + "。".join(["文字列"] * 100) + "。" + key + "。" + "。".join(["文字列"] * 100)
    found = secrets.judged([None, "", text], forest, 0.5)
    outer = [h for h in found if h[3] == "assigned"]
    assert len(outer) == 1 and outer[0][4] < 0.5
    assert [text[h[1] : h[2]] for h in found if h[4] >= 0.5] == [key]
    assert np.all([h[0] == 2 for h in found])
