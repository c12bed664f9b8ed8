"""The pipeline against its stages done one by one, and the decisions of each."""

import re
import sys
from pathlib import Path

import numpy as np
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).parents[2]))
sys.path.insert(0, str(Path(__file__).parent))
import corpus_pipeline as P  # noqa: E402
from conftest import DATA  # noqa: E402
from test_operators import ODD, SCHEMA, brute_groups  # noqa: E402

from gaptide.llm import bpe, langid, secrets  # noqa: E402
from gaptide.llm.queries import tokenizer  # noqa: E402


def test_pipeline_equals_brute_force(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    got = P.run(spark, DATA).collect()
    model = langid.learn(docs, F.lit(True))
    rows = {r["doc_id"]: r.asDict() for r in docs.collect()}
    for d in list(rows):
        raw = rows[d]["text"].encode()
        s = model.scores(langid.spectrum(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]))).max()
        if not re.search(r"[^\W\d_]", rows[d]["text"]) or (1 + s) / 2 < P.LEAST_SCORE:
            del rows[d]
    groups = brute_groups({d: r["text"] for d, r in rows.items()})
    rows = {d: r for d, r in rows.items() if groups[d][1] == d}
    forest = secrets.train()
    for r in rows.values():
        for start, end, rule in reversed(secrets.proposals(r["text"])):
            if forest.predict(np.array([secrets.features(r["text"], start, end, rule)]))[0] >= 0.5:
                r["text"] = r["text"][:start] + "[secret]" + r["text"][end:]
    # the mix: sources in order, weights 3, 1, 2, cut at twice a source's words
    import hashlib

    size = {d: len(re.findall(r"[^\x20\x09-\x0D]+", r["text"])) for d, r in rows.items()}
    names = sorted({r["source"] for r in rows.values()})
    has = {s: sum(size[d] for d, r in rows.items() if r["source"] == s) for s in names}
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(names)}
    full, total = set(), 1.5 * sum(has.values())
    while True:
        left = total - sum(2 * has[s] for s in full)
        share = {s: 2 * has[s] if s in full else weight[s] * left / sum(weight[x] for x in names if x not in full) for s in names}
        more = {s for s in names if s not in full and share[s] >= 2 * has[s]}
        if not more:
            break
        full |= more
    want = []
    coder = bpe.coder(tokenizer("word_bpe_49k.json"))
    for s in names:
        goal, at = int(share[s] + 0.5), 0
        for d in sorted((d for d, r in rows.items() if r["source"] == s), key=lambda d: (int(hashlib.md5(f"mix:{d}".encode()).hexdigest()[:15], 16), d)):
            for start in (at, at + has[s]):
                take = max(0, min(goal - start, size[d]))
                if take and 2 * take >= size[d]:
                    ids = coder.encode(rows[d]["text"])
                    want.append((d, len(ids) // 4, hashlib.sha256(ids).hexdigest()))
            at += size[d]
    assert sorted((r["doc_id"], r["n_tokens"], r["ids_sha256"]) for r in got) == sorted(want)


def test_stages_keep_the_columns_and_survive_awkward_rows(spark):
    frame = spark.createDataFrame(ODD, SCHEMA).withColumn("n_chars", F.length("text").cast("long"))
    for rows in (frame, frame.limit(0)):
        docs = rows
        for name, stage in P.STAGES[:-1]:
            docs = stage(spark, docs, DATA)
            assert docs.columns == rows.columns, name
        out = P.STAGES[-1][1](spark, docs, DATA)
        assert "doc_id" in out.columns
        out.count()
