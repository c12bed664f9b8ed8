"""Secret scans: rules propose candidates, a random forest trained on labelled findings removes false positives.

The forest sees a candidate's length, the transitions between its character classes, how much of it dictionary words
cover, signs of paths and addresses, and the words beside it. Labelled findings are a parameter; the default set is made by a seeded
generator of credentials and of what is taken for them (commit hashes, identifiers, placeholders, paths, encoded data).

Cases: null or empty text has no candidates; overlapping proposals of several rules count once (the first rule's, at the
earliest place), but a long assigned value that the forest refuses is searched for others within it; values and texts of any
length are read whole; repeated rows are scanned alike; a null key is a key like any other; an empty table gives an empty
table; `scan` reads no other columns, `redact` passes them through whatever their names.
"""

from __future__ import annotations

import random
import re
import string
from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import forget_others, ship

#: Shapes of credentials, the value in the group.
RULES = {
    "private_key": r"(-----BEGIN (?:[A-Z]+ )?PRIVATE KEY-----[A-Za-z0-9+/=\s]{16,}?-----END (?:[A-Z]+ )?PRIVATE KEY-----)",
    "cloud_key_id": r"\b((?:AKIA|ASIA)[0-9A-Z]{16})\b",
    "prefixed": r"\b((?:ghp|gho|ghs)_[A-Za-z0-9]{36}|(?:sk|pk)_(?:live|test)_[A-Za-z0-9]{16,}|xox[abp]-[A-Za-z0-9-]{10,}|AIza[A-Za-z0-9_-]{35}|eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]*)",
    "assigned": r"(?:[Kk]ey|KEY|[Tt]oken|TOKEN|[Ss]ecret|SECRET|[Pp]assword|PASSWORD|[Pp]asswd|pwd|[Cc]redential)[\"']?[ \t]{0,3}[:=][ \t]{0,3}[\"']?([^\s\"'<>,;]{8,})",
    "opaque": r"(?<![A-Za-z0-9+/_=-])((?=[A-Za-z+/_=-]*[0-9])[A-Za-z0-9+/_=-]{24,})(?![A-Za-z0-9+/_=-])",
}
#: A refused assigned value longer than this (text without white space, mostly) is searched for candidates within it.
LONG_VALUE = 256
#: Common words of code and prose.
DICTIONARY = "about access account admin after again api app application array auth back base bin block body build button cache call change char class client cloud code color column com commit config connect content context copy core count create data date default delete demo dev document down download dummy edit email end entry error event example fake file filter find first font form format from function get group handle hash have head header height help home host html http icon image import index info input insert int item java json key label lang last layout left length level lib license line link list load local log login main make map master max menu message method min mock mode model module name net new next node none null number object open option order org other output page param parse part pass password path place placeholder play plugin point post price print private process product profile project property public query read redacted release remove report request resource response result return right root row sample save schema script search secret select server service session set size source sql src start state static status string style submit system table tag target task template test text that the this time title token tool tree true type update upload url user utils value var version video view web when width window with word work write www xxx your".split()
GOOD = "key token secret password passwd pwd auth credential bearer private access login api".split()
BAD = "commit sha hash checksum digest md5 revision example sample dummy test fixture placeholder image png version uuid build id href src file path".split()


def proposals(text: str, begin: int = 0, stop: int | None = None) -> list[tuple[int, int, str]]:
    """Start, end and rule of candidates, apart from one another."""
    found, stop = [], len(text) if stop is None else stop
    for rank, (rule, pattern) in enumerate(_COMPILED.items()):
        if rule == "private_key" and "PRIVATE KEY-----" not in text or rule == "assigned" and "=" not in text and ":" not in text:
            continue
        found += [(m.start(1), rank, m.end(1), rule) for m in pattern.finditer(text, begin, stop)]
    out, last = [], -1
    for start, _, end, rule in sorted(found):
        if start >= last:
            out.append((start, end, rule))
            last = end
    return out


_COMPILED = {k: re.compile(v) for k, v in RULES.items()}
_WORDS = re.compile("|".join(sorted(DICTIONARY, key=lambda w: (-len(w), w))))
_NEAR = re.compile(r"[A-Za-z]+")
FEATURES = ("length", "digits", "upper", "lower", "symbols", "transitions", "entropy", "runs", "pairs", "covered", "slashes", "dots", "file_end", "assigned", "quoted", "good_near", "bad_near", "hex_only", "dashes_uuid", "rule")


def features(text: str, start: int, end: int, rule: str) -> list[float]:
    s = text[start:end]
    n = len(s)
    kinds = ["d" if c.isdigit() else "u" if c.isupper() else "l" if c.islower() else "s" for c in s]
    counts = np.array([s.count(c) for c in set(s)]) / n
    before, after = text[max(0, start - 40) : start], text[end : end + 20]
    near = [w.lower() for w in _NEAR.findall(before)[-4:] + _NEAR.findall(after)[:2]]
    low = s.lower()
    return [
        n,
        kinds.count("d") / n,
        kinds.count("u") / n,
        kinds.count("l") / n,
        kinds.count("s") / n,
        sum(a != b for a, b in zip(kinds, kinds[1:])) / max(1, n - 1),
        float(-(counts * np.log2(counts)).sum()),
        sum(a == b for a, b in zip(s, s[1:])) / max(1, n - 1),
        sum(abs(ord(a) - ord(b)) == 1 for a, b in zip(s, s[1:])) / max(1, n - 1),
        sum(len(m.group()) for m in _WORDS.finditer(low)) / n,
        s.count("/") / n,
        s.count(".") / n,
        float(bool(re.search(r"\.[a-z]{2,4}$", s))),
        float(bool(re.search(r"[:=]\s*[\"']?$", before))),
        float(before[-1:] in "\"'" and before != ""),
        float(sum(any(g in w for g in GOOD) for w in near)),
        float(sum(w in BAD for w in near)),
        float(bool(re.fullmatch(r"[0-9a-fA-F]+", s))),
        float(bool(re.fullmatch(r"[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}", s))),
        float(list(RULES).index(rule)),
    ]


@dataclass
class Forest:
    """Binary trees as arrays: feature (-1 at a leaf), threshold, left child, right child, share of secrets."""

    trees: list[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]

    def predict(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros(len(x))
        for feature, threshold, left, right, share in self.trees:
            at = np.zeros(len(x), np.int64)
            while (go := feature[at] >= 0).any():
                rows = np.flatnonzero(go)
                node = at[rows]
                at[rows] = np.where(x[rows, feature[node]] <= threshold[node], left[node], right[node])
            out += share[at]
        return out / len(self.trees)


def grow(x: np.ndarray, y: np.ndarray, trees: int = 30, depth: int = 10, least: int = 3, seed: int = 11) -> Forest:
    """Random forest: each tree on a bootstrap sample, the best of a few thresholds of a few features at each node (Gini)."""
    rng, out = np.random.default_rng(seed), []
    tries = max(1, int(x.shape[1] ** 0.5))
    for _ in range(trees):
        nodes: list[list[float]] = []

        def build(rows: np.ndarray, level: int) -> int:
            me, share = len(nodes), float(y[rows].mean())
            nodes.append([-1, 0.0, -1, -1, share])
            if level >= depth or len(rows) < 2 * least or share in (0.0, 1.0):
                return me
            best = (2 * share * (1 - share) - 1e-9, -1, 0.0)
            for f in rng.choice(x.shape[1], tries, replace=False):
                v = x[rows, f]
                for t in np.unique(np.quantile(v, rng.random(8))):
                    go = v <= t
                    k = int(go.sum())
                    if least <= k <= len(rows) - least:
                        p, q = y[rows[go]].mean(), y[rows[~go]].mean()
                        gini = (k * 2 * p * (1 - p) + (len(rows) - k) * 2 * q * (1 - q)) / len(rows)
                        best = min(best, (gini, int(f), float(t)))
            if best[1] >= 0:
                go = x[rows, best[1]] <= best[2]
                nodes[me][:2] = best[1], best[2]
                nodes[me][2] = build(rows[go], level + 1)
                nodes[me][3] = build(rows[~go], level + 1)
            return me

        build(rng.integers(0, len(x), len(x)), 0)
        t = np.array(nodes)
        out.append((t[:, 0].astype(np.int64), t[:, 1], t[:, 2].astype(np.int64), t[:, 3].astype(np.int64), t[:, 4]))
    return Forest(out)


def labelled(n: int = 2400, seed: int = 5) -> list[tuple[str, int]]:
    """Texts with one finding each, and whether it is a secret: a seeded generator's."""
    r = random.Random(seed)
    some = lambda letters, k: "".join(r.choice(letters) for _ in range(k))
    alnum, hexes, upper = string.ascii_letters + string.digits, "0123456789abcdef", string.ascii_uppercase + string.digits
    word = lambda: r.choice(DICTIONARY)
    prose = lambda: " ".join("".join(r.choice(["er", "th", "an", "in", "re", "la", "on", "ch", "de", "ui"]) for _ in range(r.randint(1, 4))) for _ in range(r.randint(2, 6)))
    name = lambda: r.choice(["token", "api_key", "secret", "password", "access_token", "client_secret", "auth_token", "key", "SECRET_KEY", "credential"])
    sign = lambda: r.choice([" = ", "=", ": ", " : "])
    quote = lambda v: r.choice(['"%s"', "'%s'", "%s"]) % v
    yes = [
        lambda: f"{name()}{sign()}{quote(some(hexes, r.choice([32, 40, 64])))}",
        lambda: f"{name()}{sign()}{quote(some(alnum, r.randint(16, 64)))}",
        lambda: f"{name()}{sign()}{quote(some(alnum + '+/', r.choice([40, 44, 86])))}",
        lambda: f"{name()}{sign()}{quote(some(alnum + '!@#%&*', r.randint(10, 20)))}",
        lambda: f"{r.choice(['', 'id ', 'key '])}AKIA{some(upper, 16)}",
        lambda: f"{r.choice(['', 'token '])}ghp_{some(alnum, 36)}",
        lambda: f"sk_live_{some(alnum, 24)}",
        lambda: f"AIza{some(alnum + '_-', 35)}",
        lambda: f"Bearer eyJ{some(alnum, 20)}.{some(alnum, 40)}.{some(alnum + '_-', 40)}",
        lambda: f"-----BEGIN PRIVATE KEY-----\n{some(alnum + '+/', 64)}\n{some(alnum + '+/', 40)}\n-----END PRIVATE KEY-----",
    ]
    no = [
        lambda: f"commit {some(hexes, 40)}",
        lambda: f"{r.choice(['sha256', 'checksum', 'md5', 'digest', 'build'])}{r.choice([' ', ': ', '='])}{some(hexes, r.choice([32, 40, 64]))}",
        lambda: f"uuid {some(hexes, 8)}-{some(hexes, 4)}-{some(hexes, 4)}-{some(hexes, 4)}-{some(hexes, 12)}",
        lambda: f"{name()}{sign()}{quote(r.choice(['your_', 'my_', 'example_', 'test_', 'dummy_', 'sample_']) + word() + '_' + word())}",
        lambda: f"{name()}{sign()}{quote(r.choice('x*X0.') * r.randint(8, 40))}",
        lambda: f"{name()}{sign()}{quote(word() + '.' + word() + '.' + word())}",
        lambda: f"{name()}{sign()}{r.choice(['get', 'load', 'read'])}{word().title()}{word().title()}()",
        lambda: f"{name()}{sign()}{quote('changeme123' if r.random() < 0.3 else '${' + word().upper() + '_' + word().upper() + '}')}",
        lambda: f"file {word()}/{word()}/{word()}{r.randint(0, 99)}/{word()}-{word()}.{r.choice(['js', 'png', 'html', 'css'])}",
        lambda: f"{word()}_{word()}_{word()}_{word()}_{r.randint(1, 99)}_{word()}",
        lambda: f"src data/image/png/base64/{some(alnum, 30)}/{word()}",
        lambda: f"id {some(string.digits, r.randint(24, 40))}",
        lambda: f"{name()}{sign()}{quote('1234567890abcdefghijklmnop'[: r.randint(8, 26)])}",
        lambda: f"{name()}{sign()}{prose().replace(' ', '')[:30].ljust(9, 'e')}",
        lambda: f"/{prose().replace(' ', '-')}-{r.randint(1, 999)}-{prose().replace(' ', '-')}",
    ]
    out = []
    for i in range(n):
        secret = i % 2
        out.append((f"{prose()} {r.choice(yes if secret else no)()} {prose()}", secret))
    return out


def labelled_rows(table: DataFrame, text: str = "text", label: str = "label", most: int = 20_000) -> list[tuple[str, int]]:
    """Findings of a table for `train`: at most `most` rows whose text and label aren't null, those of the smallest hashes."""
    rows = table.where(F.col(text).isNotNull() & F.col(label).isNotNull()).select(F.col(text).cast("string"), F.col(label).cast("int")).orderBy(F.xxhash64(text, label)).limit(most)
    return [(r[0], int(r[1] != 0)) for r in rows.collect()]


def train(findings: Sequence[tuple[str, int]] | None = None) -> Forest:
    rows, y = [], []
    for text, secret in findings if findings is not None else labelled():
        if spans := proposals(text):
            start, end, rule = max(spans, key=lambda s: s[1] - s[0])
            rows.append(features(text, start, end, rule))
            y.append(secret)
    return grow(np.array(rows, np.float64), np.array(y, np.float64))


def judged(texts: Sequence[str | None], forest: Forest, threshold: float) -> list[tuple[int, int, int, str, float]]:
    """Index of the text, start, end, rule and score of all candidates, in order; accepted ones are apart from one another."""
    todo, out = [(i, p) for i, t in enumerate(texts) if t for p in proposals(t)], []
    while todo:
        score = forest.predict(np.array([features(texts[i], *p) for i, p in todo]))
        out += [(i, *p, float(s)) for (i, p), s in zip(todo, score)]
        todo = [(i, q) for (i, p), s in zip(todo, score) if s < threshold and p[2] == "assigned" and p[1] - p[0] > LONG_VALUE for q in proposals(texts[i], p[0] + 1, p[1])]
    return sorted(out)


def scan(docs: DataFrame, forest: Forest | None = None, threshold: float = 0.5, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, start and length (code points), rule, value, score and is_secret: a row for each candidate."""
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(forest or train())
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget_others()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                texts = part.column(1).to_pylist()
                hits = judged(texts, sent.value, threshold)
                score = np.array([h[4] for h in hits], float)
                yield pa.RecordBatch.from_arrays(
                    [part.column(0).take(pa.array([h[0] for h in hits], pa.int64())), pa.array([h[1] for h in hits], pa.int64()), pa.array([h[2] - h[1] for h in hits], pa.int64()), pa.array([h[3] for h in hits], pa.string()), pa.array([texts[h[0]][h[1] : h[2]] for h in hits], pa.string()), pa.array(score, pa.float64()), pa.array(score >= threshold, pa.bool_())],
                    ["key", "start", "length", "rule", "value", "score", "is_secret"],
                )

    return docs.select(F.col(key).alias("key"), F.col(text).cast("string")).mapInArrow(run, f"key {kind}, start long, length long, rule string, value string, score double, is_secret boolean").withColumnRenamed("key", key)


def redact(docs: DataFrame, forest: Forest | None = None, threshold: float = 0.5, text: str = "text", mark: str = "[secret]") -> DataFrame:
    """docs with each secret in the text replaced by a mark; other columns and rows stay as they are."""
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(forest or train())
    place, names = docs.columns.index(text), docs.columns
    body = docs.select(*[F.col(c).cast("string").alias(c) if c == text else F.col(c) for c in names])
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in body.schema.fields)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget_others()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                out = part.column(place).to_pylist()
                for i, start, end, _, score in reversed(judged(out, sent.value, threshold)):
                    if score >= threshold:
                        out[i] = out[i][:start] + mark + out[i][end:]
                yield pa.RecordBatch.from_arrays([pa.array(out, pa.string()) if i == place else c for i, c in enumerate(part.columns)], names)

    return body.mapInArrow(run, schema)
