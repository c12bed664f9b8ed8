"""Training-data operators: brute force, round trips, held-out accuracy, and awkward rows."""

import hashlib
import re
import sys
import zlib
from array import array
from collections import Counter, defaultdict
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).parents[1]))
from conftest import DATA  # noqa: E402
from oracle import connect, same  # noqa: E402

from gaptide.llm import ann, bpe, fingerprint, jaccard, langid, license, mixing, queries, secrets, tokencount, warc  # noqa: E402
from gaptide.llm.base import NOT_ALNUM, shingles, words  # noqa: E402

LONG = "wort " * 30_000
ODD = [(1, None, None, None, 5), (2, "", "en", "b", None), (3, "   \n\t ", "en", "a", 1), (4, "12345 !!! ???", None, "", 2), (5, LONG, "de", "a", 3), (6, "the cat sat on the mat and went home", "en", "a", 4), (6, "the cat sat on the mat and went home", "en", "a", 4), (None, "orphan text of no document at all here", "en", None, 4), (8, "Grüße 日本語 😀 İΣ <|endoftext|> it's", "de", "ü", 1), (-9, "two words", "en", "a", 9)]
SCHEMA = "doc_id long, text string, lang string, source string, extra int"
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet")


@pytest.fixture(scope="module")
def rows(docs):
    return {r["doc_id"]: r for r in docs.collect()}


@pytest.mark.parametrize("name", sorted(queries.SQL))
def test_query_equals_sql(spark, name):
    same(queries.QUERIES[name](spark, DATA).toPandas(), connect(DATA).sql(queries.SQL[name]).df())


# --- mixing


def test_mixing_targets_and_limits(spark, odd, empty):
    r = mixing.mix(odd, mixing.ramps((3, 1, 2)), keep=("doc_id",)).toPandas()
    assert len(r) == len(ODD) and (r["taken"] <= 2 * r["size"]).all()
    per = spark.createDataFrame(r).groupBy("source_size", "target").agg(F.sum("taken").alias("taken")).collect()
    assert all(abs(p["taken"] - p["target"]) < 1 for p in per if p["target"] is not None)
    assert mixing.mix(empty, mixing.ramps((3, 1, 2))).count() == 0
    again = mixing.mix(odd.repartition(7), mixing.ramps((3, 1, 2)), keep=("doc_id",)).toPandas()
    key = ["doc_id", "size", "taken"]
    assert sorted(r[key].fillna(-1).values.tolist()) == sorted(again[key].fillna(-1).values.tolist())


def test_mixing_comes_near_each_target(docs):
    r = mixing.mix(docs, mixing.ramps((3, 1, 2)), keep=("doc_id",)).join(docs.select("doc_id", "source"), "doc_id").groupBy("source").agg(F.sum("taken").alias("taken"), F.max("target").alias("target"), F.max("source_size").alias("size")).collect()
    assert all(abs(x["taken"] - x["target"]) <= 1 for x in r)
    assert abs(sum(x["target"] for x in r) - 1.5 * sum(x["size"] for x in r)) < 1e-6


def test_schedule_inversion(spark):
    s = [(0.0, 1.0), (0.5, 3.0), (1.0, 0.0)]
    whole = mixing.integral(s)
    got = spark.range(11).select(mixing.invert(s, F.col("id") / 10.0).alias("t")).toPandas()["t"].to_numpy()
    assert (np.diff(got) > 0).all()
    for share, t in zip(np.arange(11) / 10, got):
        grid = np.linspace(0, t, 20001)
        area = np.trapezoid(np.interp(grid, [0, 0.5, 1], [1, 3, 0]), grid)
        assert abs(area / whole - share) < 1e-6


# --- n-gram join


def brute_groups(texts: dict) -> dict:
    sets = {}
    for d, t in texts.items():
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")))
        sets[d] = {" ".join(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {" ".join(w)} if w else set()
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {d: (len(sets[d]), find(d)) for d in ids}


@pytest.mark.parametrize("small,large", [(256, 4096), (3, 8)])
def test_join_equals_brute_force_on_chains_and_copies(spark, monkeypatch, small, large):
    monkeypatch.setattr(jaccard, "SMALL_BLOCK", small)
    monkeypatch.setattr(jaccard, "LARGE_BLOCK", large)
    gen = np.random.default_rng(5)
    vocabulary = [f"w{i}" for i in range(4000)]
    texts, k = {}, 0
    for base in range(12):
        w = list(gen.choice(vocabulary, int(gen.integers(6, 150))))
        for _ in range(9):  # a chain: each copy is edited a little more
            texts[k * 7] = " ".join(w)
            k += 1
            for _ in range(int(gen.integers(0, 3))):
                w[int(gen.integers(len(w)))] = str(gen.choice(vocabulary))
    passage = " ".join(gen.choice(vocabulary, 60))
    for i in range(40):
        texts[10_000 + i] = passage + " " + " ".join(gen.choice(vocabulary, int(gen.integers(3, 60))))
    frame = spark.createDataFrame([(d, t) for d, t in texts.items()], "doc_id long, text string").repartition(5)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard.join_groups(frame).collect()}
    assert got == brute_groups(texts)


def test_join_awkward_rows(odd, empty):
    got = jaccard.join_groups(odd).collect()
    assert len(got) == len(ODD)
    by = defaultdict(list)
    for r in got:
        by[r["doc_id"]].append((r["n_shingles"], r["component_id"]))
    assert by[1] == [(0, 1)] and by[2] == [(0, 2)] and by[3] == [(0, 3)] and by[-9] == [(1, -9)]
    assert by[6] == [(5, 6), (5, 6)] and by[None][0][1] is None and by[5] == [(1, 5)]
    assert jaccard.join_groups(empty).count() == 0
    kept = jaccard.one_of_each(odd)
    assert kept.columns == odd.columns and kept.where("doc_id = 6").count() == 1 and kept.where("doc_id is null").count() == 1


def test_tree_finds_all_pairs_that_may_be_similar():
    gen = np.random.default_rng(2)
    points = gen.integers(0, 6, (150, 16)).astype(np.int32)
    points[75:] = np.maximum(points[:75] + gen.integers(-1, 2, (75, 16)), 0)
    sizes, roots = points.sum(axis=1).astype(np.int64), np.arange(150)
    got = {tuple(sorted(p)) for i, j in jaccard.CountTree(points, sizes).pairs(roots) for p in zip(i.tolist(), j.tolist())}
    want = {(i, j) for i in range(150) for j in range(i + 1, 150) if 7 * np.minimum(points[i], points[j]).sum() >= 3 * (sizes[i] + sizes[j])}
    assert {p for p in want if 4 * min(sizes[list(p)]) >= 3 * max(sizes[list(p)])} <= got


def test_heads_hold_the_promised_number_of_common_shingles():
    gen = np.random.default_rng(0)
    for _ in range(300):
        n = int(gen.integers(5, 400))
        pool = gen.permutation(2000)
        a = set(pool[:n].tolist())
        drop, extra = int(gen.integers(0, n // 4 + 1)), int(gen.integers(0, n // 4 + 1))
        b = set(list(a)[drop:]) | set(pool[n : n + extra].tolist())
        if 4 * len(a & b) >= 3 * len(a | b):
            heads = [set(sorted(s)[: jaccard.lead_size(len(s))]) for s in (a, b)]
            assert len(heads[0] & heads[1]) >= max(1, min(jaccard.least_shared(len(a)), jaccard.least_shared(len(b))))


# --- language


def test_language_held_out_accuracy(spark, docs):
    r = queries.op3_language(spark, DATA).join(docs.select("doc_id", "lang"), "doc_id").toPandas()
    assert (r["held_out"] == [zlib.crc32(str(d).encode()) % 4 == 2 for d in r["doc_id"]]).all()
    held = r[r["held_out"]]
    assert (held["lang_pred"] == held["lang"]).mean() >= 0.97 and r["score"].between(0, 1).all()


def test_language_awkward_rows(odd, empty, docs):
    model = langid.learn(docs, F.lit(True))
    got = langid.predict(odd, model)
    assert got.columns == [*odd.columns, "lang_pred", "score"]
    by = {r["doc_id"]: r for r in got.collect()}
    assert [by[k]["lang_pred"] for k in (1, 2, 3, 4)] == ["und"] * 4 and by[1]["score"] == 0 and by[5]["lang_pred"] != "und"
    assert langid.predict(empty, model).count() == 0
    none = langid.learn(empty, F.lit(True))
    assert {r["lang_pred"] for r in langid.predict(odd, none).collect()} == {"und"}


# --- WARC


def test_warc_records(spark):
    html = "<html><head><title>A\nB</title><style>x</style></head><body><!-- no --><p>one &amp; two</p><p>&#233;&#x41;&bogus; &#99999999;</p><script>var a='<p>';</script><a href='/x'>link</a></body></html>"
    pages = spark.createDataFrame([(1, "http://a/b", html), (2, None, None), (None, "u", "")], "page_id long, url string, html string")
    got = warc.serialised(warc.derive(pages)).collect()
    assert len(got) == 9
    by = {(r["page_id"], r["kind"]): r for r in got}
    assert by[1, "conversion"]["block"] == "A\nB\none & two\néA&bogus; &#99999999;\nlink"
    assert by[1, "conversion"]["refers_to"] == by[1, "response"]["record_id"] == by[1, "metadata"]["refers_to"]
    for r in got:
        head, block = bytes(r["record"]).split(b"\r\n\r\n", 1)
        assert len(block) == r["content_length"] + 4 and block.endswith(b"\r\n\r\n")
        assert f"sha256:{hashlib.sha256(block[:-4]).hexdigest()}" == r["block_digest"]
        assert head.startswith(b"WARC/1.1\r\nWARC-Type: " + r["kind"].encode())
    assert by[1, "response"]["payload_digest"] == f"sha256:{hashlib.sha256(html.encode()).hexdigest()}"
    assert warc.derive(pages.limit(0)).count() == 0


# --- BPE


def library():
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(queries.tokenizer("word_bpe_49k.json"))
    t.no_truncation()
    t.no_padding()
    return t


def test_bpe_equals_the_library(odd, empty, rows):
    t, path = library(), queries.tokenizer("word_bpe_49k.json")
    c = bpe.coder(path)
    texts = [r["text"] for r in rows.values()] + [r[1] or "" for r in ODD] + ["a" * 3000, "x\x1cy\x85z　q", "é ﬁ Ⅷ ½ don't WE'LL", "<|startoftext|><|endoftext|>", "<|start", "ΑΣ Σ ΣΑ"]
    for x in texts:
        want = t.encode(x, add_special_tokens=False).ids
        assert array("I", want).tobytes() == c.encode(x), x[:50]
        assert t.decode(want, skip_special_tokens=False) == c.decode(c.encode(x))
    got = bpe.digests(bpe.round_trip(odd, path)).collect()
    assert len(got) == len(ODD)
    assert next(r for r in got if r["doc_id"] == 1)["ids_sha256"] == hashlib.sha256(b"").hexdigest()
    assert bpe.round_trip(empty, path).count() == 0


def test_bpe_random_texts():
    from hypothesis import given, settings
    from hypothesis import strategies as st

    t, c = library(), bpe.coder(queries.tokenizer("word_bpe_49k.json"))

    @settings(max_examples=300, deadline=None)
    @given(st.text(alphabet=st.one_of(st.sampled_from("abc'stdlérΣ \n\t\x1c\x85<|>endofstartxt12½"), st.characters(codec="utf-8", categories=("L", "N", "P", "S", "Z"), max_codepoint=0x2FFF)), max_size=40))
    def check(x):
        want = t.encode(x, add_special_tokens=False).ids
        assert array("I", want).tobytes() == c.encode(x)

    check()


def test_forced_boundaries_never_split_a_token():
    c = bpe.coder(queries.tokenizer("word_bpe_49k.json"))
    assert c.forced(b"zq\x00zq") != [b"zq\x00zq"]
    for token in list(c.ids)[1000:3000]:
        body = token.removesuffix(c.end)
        data = bytes(c.letters.index(x) for x in body)
        assert c.forced(data) == [data]


# --- fingerprints


def test_fingerprints_next_edits_and_likeness(spark, docs, rows):
    got = {r["doc_id"]: r for r in queries.op6_fingerprints(spark, DATA).collect()}
    order = sorted(rows, reverse=True)
    better = 0
    for d, n in zip(order, order[1:] + order[:1]):
        t, x = rows[d]["text"], rows[n]["text"]
        k = len(t) // 3
        edited = t[: len(t) - k] + x[:k]
        assert got[d]["n_chars"] == len(t) and got[d]["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        better += got[d]["near_edited"] >= got[d]["near_next"]
        if t == edited:
            assert got[d]["near_edited"] == 1
    assert better >= 0.97 * len(order)


def test_fingerprints_awkward_rows(spark, odd, empty):
    got = fingerprint.edited_likeness(odd).collect()
    assert len(got) == len(ODD)
    same_text = [r["fingerprint"] for r in got if r["doc_id"] == 6]
    assert same_text[0] == same_text[1]
    assert fingerprint.edited_likeness(empty).count() == 0
    one = fingerprint.edited_likeness(spark.createDataFrame([(7, "abcdef")], "doc_id long, text string")).first()
    assert one["edited"] == "abcdab" and one["near_next"] == 1.0
    assert fingerprint.edited_likeness(spark.createDataFrame([(None, "abc"), (None, "xyz")], "doc_id long, text string")).count() == 2


def test_fingerprints_are_homomorphic(spark):
    f = spark.createDataFrame([("one\ntwo\nthree", "three\none\ntwo", "one\nthree", "two")], "a string, b string, c string, d string")
    v = {x: fingerprint.vector(F.col(x)) for x in "abcd"}
    p = fingerprint.printed
    r = f.select((p(v["a"]) == p(v["b"])).alias("order"), (p(v["a"]) == p(fingerprint.add(v["c"], v["d"]))).alias("insert"), (p(fingerprint.remove(v["a"], v["d"])) == p(v["c"])).alias("delete"), (p(v["a"]) != p(v["c"])).alias("differs")).first()
    assert all(r)


def test_fingerprint_likeness_follows_shared_paragraphs(spark):
    text = [f"paragraph number {i} stands here" for i in range(200)]
    cases = [(k, "\n".join(text), "\n".join(text[:k] + [f"other {i} thing" for i in range(200 - k)])) for k in (0, 50, 100, 150, 200)]
    f = spark.createDataFrame(cases, "k int, a string, b string")
    got = f.select("k", fingerprint.likeness(fingerprint.vector(F.col("a")), fingerprint.vector(F.col("b"))).alias("s")).collect()
    assert all(abs(r["s"] - r["k"] / 200) < 0.2 for r in got) and got[-1]["s"] == 1


# --- token counts


def brute_count(word: str, scores: dict, byte: int) -> int:
    path, best = tokencount.MARK + word, [(0, 0)]
    for n in range(1, len(path) + 1):
        width = len(path[n - 1].encode())
        best.append(max([(best[n - 1][0] + byte * width, best[n - 1][1] - width)] + [(best[k][0] + scores[path[k:n]], best[k][1] - 1) for k in range(n) if path[k:n] in scores]))
    return -best[-1][1]


def test_token_counts_equal_brute_force(docs, odd, empty, rows):
    path = queries.tokenizer("piece_bpe_32k.model")
    scores = tokencount.rank_scores(path)
    byte = min(scores.values()) - tokencount.SCALE
    for frame, source in ((docs, [(r["doc_id"], r["text"]) for r in list(rows.values())[:40]]), (odd, [r[:2] for r in ODD])):
        got = Counter((r["doc_id"], r["n_words"], r["n_tokens"]) for r in tokencount.count_tokens(frame, path).collect())
        memo = {}
        for d, t in source:
            w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
            n = sum(memo[x] if x in memo else memo.setdefault(x, brute_count(x, scores, byte)) for x in w)
            assert got[d, len(w), n] >= 1
    assert tokencount.count_tokens(empty, path).count() == 0


# --- licences


def brute_licenses(text: str, library: license.Library) -> set:
    raw = np.frombuffer(text.encode(), np.uint8)
    s, _ = shingles(*words(raw, np.array([0, len(raw)]), between=NOT_ALNUM)[:2], 1)
    return {library.names[t] for t, own in enumerate(library.sets) for i in range(len(s)) if i % library.levels[t] == 0 and np.isin(own, s[i : i + 2 * library.levels[t]]).mean() >= 0.75}


def test_license_scan_equals_exhaustive_windows(spark, docs, odd, empty, rows):
    lib = license.Library.of(license.TEMPLATES, 0.75, 0.999)
    got = defaultdict(set)
    for r in license.scan(docs).collect():
        got[r["doc_id"]].add(r["license"])
    want = {d: x for d, r in rows.items() if (x := brute_licenses(r["text"], lib))}
    assert dict(got) == want
    filler = " ".join(f"f{i}" for i in range(300))
    planted = spark.createDataFrame([(i, f"{filler} {t} {filler}") for i, t in enumerate(license.TEMPLATES.values())], "doc_id long, text string")
    found = {(r["doc_id"], r["license"]) for r in license.scan(planted).collect()}
    assert {(i, n) for i, n in enumerate(license.TEMPLATES)} <= found
    assert license.scan(odd).count() == 0 and license.scan(empty).count() == 0


def test_band_settings():
    floor = license.jaccard_floor(0.75)
    b = license.bands_for(floor, 0.999)
    assert 1 - (1 - floor) ** b >= 0.999 > 1 - (1 - floor) ** (b - 1)


# --- secrets


def test_secret_forest_on_unseen_findings():
    forest, right, n = secrets.train(), 0, 0
    for text, secret in secrets.labelled(600, seed=77):
        spans = secrets.proposals(text)
        guess = any(forest.predict(np.array([secrets.features(text, *s)]))[0] >= 0.5 for s in spans)
        right, n = right + (guess == bool(secret)), n + 1
    assert right / n >= 0.95


def test_secret_scan_and_redaction(spark, docs, odd, empty, rows):
    got = secrets.scan(docs).collect()
    forest = secrets.train()
    want = sorted((d, s, e - s, rule) for d, r in rows.items() for s, e, rule in secrets.proposals(r["text"]))
    assert sorted((r["doc_id"], r["start"], r["length"], r["rule"]) for r in got) == want
    for r in got:
        assert rows[r["doc_id"]]["text"][r["start"] : r["start"] + r["length"]] == r["value"]
    planted = {d for d, r in rows.items() if re.search(r'token = "[0-9a-f]{40}"|AKIA[0-9A-Z]{16}', r["text"])}
    assert planted <= {r["doc_id"] for r in got if r["is_secret"]}
    clean = secrets.redact(docs, forest)
    assert clean.columns == docs.columns and clean.count() == docs.count()
    assert not [r for r in clean.collect() if re.search(r'token = "[0-9a-f]{40}"|AKIA[0-9A-Z]{16}', r["text"])]
    assert secrets.redact(odd, forest).exceptAll(odd).count() == 0 and secrets.scan(empty, forest).count() == 0
    assert secrets.scan(spark.createDataFrame([(1, "see commit 9fceb02d0ae598e95dc970b74767f19372d61af8 for api_key = your_example_key here")], "doc_id long, text string"), forest).where("is_secret").count() == 0


# --- nearest neighbours


def test_neighbours_recall_and_ties(spark):
    e = spark.read.parquet(f"{DATA}/embeddings.parquet")
    pdf = e.toPandas()
    x = np.stack(pdf["embedding"]).astype(float)
    x /= np.linalg.norm(x, axis=1)[:, None]
    got = queries.op10_neighbours(spark, DATA).toPandas()
    hits = 0
    for q in np.flatnonzero(pdf["vec_id"] % 50 == 0):
        cos = x @ x[q]
        cos[q] = -9
        best = set(pdf["vec_id"].to_numpy()[np.lexsort((pdf["vec_id"], -np.round(cos, 12)))[:5]])
        own = got[got["query_id"] == pdf["vec_id"][q]].sort_values("rank")
        hits += len(best & set(own["vec_id"]))
        assert own["rank"].tolist() == [1, 2, 3, 4, 5] and (np.diff(own["score"]) <= 0).all()
    assert hits >= 0.9 * len(got)


def test_neighbours_awkward_rows(spark):
    nan = float("nan")
    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [2.0, 0.0]), (3, [0.0, 1.0]), (4, None), (5, [0.0, 0.0]), (6, [nan, 1.0]), (7, [None, 1.0]), (8, [1.0]), (50, [0.0, -1.0]), (None, [1.0, 1.0]), (9, [float("inf"), 0.0])]
    v = spark.createDataFrame([(a, b, "x") for a, b in rows], "vec_id long, embedding array<float>, rank string")
    got = ann.nearest(v, F.pmod(F.col("id"), F.lit(50)) == 0).orderBy("query_id", "rank").collect()
    zero = [(r["vec_id"], round(r["score"], 9)) for r in got if r["query_id"] == 0]
    assert zero == [(1, 1.0), (2, 1.0), (3, 0.0), (50, 0.0)]
    assert len([r for r in got if r["query_id"] == 50]) == 4
    assert ann.nearest(v.limit(0), F.col("id") == 0).count() == 0


def test_chi_square():
    assert abs(ann.chi_square_cdf(15.507, 8) - 0.95) < 1e-4 and abs(ann.chi_square_quantile(0.95, 8) - 15.507) < 1e-2
