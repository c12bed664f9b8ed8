"""Language identification by a string kernel.

The kernel of two stretches of text is the number of hashed byte n-grams (a blended spectrum of lengths 1 to 4) that both
hold, over the root of the product of the numbers that each holds: presence, not frequency. A text is cut into even
stretches of at most STRETCH bytes, all of them are read, and the kernel of two texts is the mean over their pairs of
stretches; capitals count as small letters; so hashed places don't fill up however long a text is, and a text's regression is the mean of its stretches'.
Landmark texts of all lengths give Nyström features; one ridge regression per language, against the rest, is solved on a
bounded sample of labelled texts, and all texts are scored in batches by one matrix product.

The sample's bound (landmarks and texts for each language) is a parameter; everything else covers all rows.

Cases: a text that is null or has no letter is `und` with score 0; null languages are not learned from; with nothing to
learn from, every text is `und`; repeated rows are predicted alike; long texts are read whole; an empty table gives an
empty table; other columns pass through, but for those that have the names of the two that are added.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .base import attach, forget_others, ship, utf8

BITS = 12
#: Most bytes whose n-grams are hashed to one row of 2**BITS places, and rows made at a time.
STRETCH, AT_ONCE = 2048, 256
LETTER = regex.compile(r"\p{L}")
UNKNOWN = "und"


def folded(b: np.ndarray) -> np.ndarray:
    """Bytes of UTF-8 text with A to Z, and the accented capitals of the two-byte block C3 80 to C3 9E, as small letters."""
    low = b + np.uint8(32) * ((b >= 65) & (b <= 90))
    accented = np.flatnonzero((b[:-1] == 0xC3) & (b[1:] >= 0x80) & (b[1:] <= 0x9E) & (b[1:] != 0x97)) + 1
    low[accented] += np.uint8(32)
    return low


def presence(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, longest: int = 4) -> np.ndarray:
    """Presence (0 or 1) of hashed n-grams, a row for each stretch."""
    out = np.zeros((len(starts), 1 << BITS), np.float32)
    for i in range(len(out)):
        b = folded(raw[starts[i] : ends[i]]).astype(np.uint32)
        row, gram = out[i], np.zeros(len(b), np.uint32)
        for n in range(1, longest + 1):
            if len(b) < n:
                break
            gram = gram[: len(b) - n + 1] * np.uint32(257) + b[n - 1 :]
            row[((gram + np.uint32(n)) * np.uint32(2654435761)) >> np.uint32(32 - BITS)] = 1
    return out


def unit(x: np.ndarray) -> np.ndarray:
    n = np.sqrt(x.sum(axis=1, keepdims=True))
    return x / np.maximum(n, 1)


def spectrum(raw: np.ndarray, offsets: np.ndarray, longest: int = 4) -> np.ndarray:
    """Mean of the unit presence rows of all stretches, a row for each text. A stretch also reads the bytes that end the n-grams begun in it."""
    size = np.diff(offsets)
    parts = np.maximum(1, -(-size // STRETCH))
    owner = np.repeat(np.arange(len(size)), parts)
    place = np.arange(len(owner)) - np.repeat(np.cumsum(parts) - parts, parts)
    starts = offsets[owner] + place * size[owner] // parts[owner]
    ends = np.minimum(offsets[owner] + (place + 1) * size[owner] // parts[owner] + longest - 1, offsets[owner + 1])
    out = np.zeros((len(size), 1 << BITS), np.float32)
    for at in range(0, len(owner), AT_ONCE):
        own = owner[at : at + AT_ONCE]
        rows = unit(presence(raw, starts[at : at + AT_ONCE], ends[at : at + AT_ONCE], longest))
        first = np.flatnonzero(np.diff(own, prepend=-1))
        out[own[first]] += np.add.reduceat(rows, first, axis=0)
    return out / parts[:, None].astype(np.float32)


@dataclass
class KernelModel:
    langs: list[str]
    landmarks: np.ndarray  # profiles
    weights: np.ndarray  # landmarks x languages
    bias: np.ndarray

    def scores(self, x: np.ndarray) -> np.ndarray:
        return x @ self.landmarks.T @ self.weights + self.bias


def fit(x: np.ndarray, langs: list[str], landmarks_each: int = 48, ridge: float = 1e-3) -> KernelModel:
    """From profiles in the order of their texts' lengths within each language: landmarks are taken evenly from that order."""
    names = sorted(set(langs))
    y = np.array([names.index(v) for v in langs])
    rows = [np.flatnonzero(y == k) for k in range(len(names))]
    marks = x[np.concatenate([r[np.arange(min(len(r), landmarks_each)) * len(r) // min(len(r), landmarks_each)] for r in rows])] if names else x[:0]
    if not names:
        return KernelModel([], marks, np.zeros((0, 0), np.float32), np.zeros(0, np.float32))
    value, vector = np.linalg.eigh((marks @ marks.T).astype(np.float64))
    held = value > 1e-6 * value.max()
    root = vector[:, held] / np.sqrt(value[held])
    z = (x @ marks.T) @ root
    goal = np.where(y[:, None] == np.arange(len(names)), 1.0, -1.0)
    share = 1 / (len(names) * np.bincount(y)[y])[:, None]  # each language counts the same, however many of its texts there are
    mid, base = (share * z).sum(axis=0), (share * goal).sum(axis=0)
    zc = z - mid
    w = np.linalg.solve(zc.T @ (share * zc) + ridge * np.eye(zc.shape[1]), zc.T @ (share * (goal - base)))
    return KernelModel(names, marks, (root @ w).astype(np.float32), (base - mid @ w).astype(np.float32))


def _profile_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            raw, offsets = utf8(part.column(1))
            packed = [zlib.compress(p.tobytes()) for p in spectrum(raw, offsets).astype(np.float16)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(np.diff(offsets), pa.int64()), pa.array(packed, pa.binary())], ["lang", "size", "profile"])


def learn(docs: DataFrame, usable: Column, lang: str = "lang", text: str = "text", key: str = "doc_id", each: int = 240, landmarks_each: int = 48) -> KernelModel:
    """Fit on at most `each` labelled texts a language, those with the smallest hashes of their keys; only packed profiles reach the driver."""
    ship(docs.sparkSession)
    held = docs.where(usable & F.col(lang).isNotNull() & F.col(text).isNotNull()).select(F.col(key).alias("k"), F.col(lang).cast("string").alias("lang"), F.col(text).cast("string").alias("text"))
    counts = held.groupBy("lang").agg(F.count(F.lit(1)).alias("n"))
    draw = F.pmod(F.xxhash64("k"), F.lit(1 << 30)) / float(1 << 30)
    few = attach(held, counts, ["lang"]).where(draw * F.col("n") < 2 * each)  # before any row is moved
    few = few.withColumn("draw", draw).withColumn("r", F.row_number().over(W.partitionBy("lang").orderBy("draw", "k"))).where(F.col("r") <= each)
    rows = few.select("lang", "text").mapInArrow(_profile_rows, "lang string, size long, profile binary").collect()
    rows.sort(key=lambda r: (r["lang"], r["size"], bytes(r["profile"])))
    x = np.array([np.frombuffer(zlib.decompress(r["profile"]), np.float16) for r in rows], np.float32).reshape(len(rows), 1 << BITS)
    return fit(x, [r["lang"] for r in rows], landmarks_each)


def predict(docs: DataFrame, model: KernelModel, text: str = "text", rows: int = 256, out: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """All columns of docs, and two of the names in out: the language, and half of 1 plus the best regression, within 0 and 1. Columns of docs with these names give way."""
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(model)
    docs = docs.drop(*out)
    names = docs.columns
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields) + f", `{out[0]}` string, `{out[1]}` double"
    place = names.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = sent.value
        forget_others()
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                column = part.column(place)
                lettered = np.array([t is not None and LETTER.search(t) is not None for t in column.to_pylist()], bool)
                guess, score = np.full(len(column), UNKNOWN, object), np.zeros(len(column))
                if m.langs and lettered.any():
                    s = m.scores(spectrum(*utf8(column)))
                    best = s.argmax(axis=1)
                    guess[lettered] = np.array(m.langs, object)[best[lettered]]
                    score[lettered] = np.clip((1 + s.max(axis=1).astype(float)) / 2, 0, 1)[lettered]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(guess, pa.string()), pa.array(score, pa.float64())], [*names, *out])

    return docs.mapInArrow(run, schema)
