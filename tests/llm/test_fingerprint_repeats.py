"""Likeness of documents with repeated paragraphs against the exact likeness of their multisets."""

import re
import sys
from collections import Counter
from pathlib import Path

from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).parents[1]))
from conftest import DATA  # noqa: E402

from gaptide.llm import fingerprint  # noqa: E402


def multiset(text: str) -> Counter:
    marked = re.sub(r"((?:[^ \n]+ ){6})", "\\1\n", re.sub(r"([.!?]) ", "\\1\n", text))
    return Counter(p for p in marked.split("\n") if p)


def exact(a: str, b: str) -> float:
    x, y = multiset(a), multiset(b)
    both = x.total() + y.total()
    return 1 - ((x - y).total() + (y - x).total()) / both if both else 1.0


def test_repeated_lines_count_once_each(spark):
    other = [f"other line {i} of its own" for i in range(100)]
    cases = []
    for k in (0, 1, 10, 50, 90):
        a = "\n".join(["the same line again"] * 100 + other)
        cases.append((a, "\n".join(["the same line again"] * (100 - k) + other)))
    cases.append(("x\n" * 40 + "y\n" * 30, "y\n" * 30 + "x\n" * 39 + "z\n"))
    f = spark.createDataFrame(cases, "a string, b string")
    got = f.select("a", "b", fingerprint.likeness(fingerprint.vector(F.col("a")), fingerprint.vector(F.col("b"))).alias("s")).collect()
    assert [(round(r["s"], 2), round(exact(r["a"], r["b"]), 2)) for r in got if abs(r["s"] - exact(r["a"], r["b"])) > 0.15] == []


def test_likeness_to_edited_form_is_near_the_exact_one(spark):
    lines = "\n".join
    docs = spark.read.parquet(f"{DATA}/documents.parquet").select("doc_id", "text")
    repeated = [(1_000_000 + i, lines([f"head {i} line {j}" for j in range(30)] + [f"again {i}"] * 60 + [f"tail {i} line {j}" for j in range(10)])) for i in range(20)]
    text = docs.unionByName(spark.createDataFrame(repeated, "doc_id long, text string"))
    was = {r["doc_id"]: r["text"] for r in text.collect()}
    order = sorted(was, reverse=True)
    following = dict(zip(order, order[1:] + order[:1]))
    ratios, off = [], []
    for r in fingerprint.edited_likeness(text).collect():
        t, n = was[r["doc_id"]], was[following[r["doc_id"]]]
        for got, want in ((r["near_edited"], exact(t, r["edited"])), (r["near_next"], exact(t, n))):
            off.append(abs(got - want))
            ratios.append(off[-1] / max(1 - want, 1e-9))
    # a mean of 64 squares: a standard deviation of sqrt(2 / 64) of the difference
    assert max(ratios) < 4 * (2 / 64) ** 0.5 and sum(off) / len(off) < 0.1


def test_next_documents_over_many_buckets_and_null_keys(spark):
    texts = [f"text number {i} " + "x" * (i % 7) for i in range(300)]
    for keys in ([i // 3 * 5 for i in range(300)], [None if i % 3 else i for i in range(300)], [None] * 300):
        rows = spark.createDataFrame(list(zip(keys, texts)), "doc_id long, text string").repartition(7)
        ranked = rows.withColumn("h", F.xxhash64("text")).collect()
        order = sorted(ranked, key=lambda r: (r[0] is None, -(r[0] or 0), -r["h"] if r[0] is None else 0, r["text"]))
        want = {r["text"]: n["text"] for r, n in zip(order, order[1:] + order[:1])}
        got = fingerprint.with_next(fingerprint.fingerprints(rows), rows_in_bucket=4).select("text", "next_text").collect()
        assert len(got) == 300 and {r["text"]: r["next_text"] for r in got} == want
