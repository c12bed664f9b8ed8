"""BPE encoding and decoding with forced boundaries.

Two neighbouring bytes that no vocabulary token holds side by side can never be merged, so a pre-token is cut between
them; each fragment is encoded alone and the results are put together. The vocabulary file is a parameter.

Cases: null text is the empty text (no ids, empty decoded text); an empty table gives an empty table; repeated rows give
repeated rows; a text may be of any length (long fragments merge by a heap); columns besides the two named pass through
the query untouched because only those two are read; a null key is a key like any other.
"""

from __future__ import annotations

import heapq
import json
import unicodedata
from array import array
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import forget_others, keep, ship

#: What the pattern language of the tokenizer file calls white space.
SPACE = "\\x09-\\x0D\\x20\\x85\\xA0\\u1680\\u2000-\\u200A\\u2028\\u2029\\u202F\\u205F\\u3000"
#: White space of Python's str.split that is none there.
ODD = regex.compile("[\\x1C-\\x1F]")
BLANK = regex.compile(f"[{SPACE}]+")
LONG = 64


def byte_letters() -> list[str]:
    """The letter that stands for each byte: printable Latin-1 stands for itself, the others follow from 256 on."""
    shown = {*range(33, 127), *range(161, 173), *range(174, 256)}
    letters, extra = [], 256
    for b in range(256):
        letters.append(chr(b if b in shown else extra))
        extra += b not in shown
    return letters


class Words(dict):
    """Encoded chunks, kept up to a bound and then forgotten; long ones are never kept. A key is a text, or a pair of a text and a mark."""

    def __init__(self, make, most: int):
        super().__init__()
        self.make, self.most = make, most

    def __missing__(self, key):
        value = self.make(key)
        if len(key if isinstance(key, str) else key[0]) <= LONG:
            if len(self) >= self.most:
                self.clear()
            self[key] = value
        return value


class ForcedBoundaryBPE:
    def __init__(self, path: str, most: int = 400_000):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.end = model.get("end_of_word_suffix") or ""
        self.ids: dict[str, int] = model["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = [""] * (1 + max([*self.ids.values(), *self.special.values()]))
        for t, i in [*self.ids.items(), *self.special.items()]:
            self.tokens[i] = t
        pairs = (m if isinstance(m, list) else m.split(" ") for m in model["merges"])
        self.rank = {(a, b): (r, a + b) for r, (a, b) in enumerate(pairs)}
        self.letters = byte_letters()
        byte_of = {c: b for b, c in enumerate(self.letters)}
        inside = [bytearray(256) for _ in range(256)]
        for t in self.ids:
            body = t[: -len(self.end)] if self.end and t.endswith(self.end) else t
            seq = [byte_of[c] for c in body if c in byte_of]
            for a, b in zip(seq, seq[1:]):
                inside[a][b] = 1
        self.inside = inside
        split = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.pattern = regex.compile(split.replace("\\s", SPACE))
        self.cut = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None
        self.mark = [t[:2] for t in self.special]
        self.fragments = Words(self._merge, most // 2)
        self.chunks = Words(self._chunk, most)

    def forced(self, data: bytes) -> list[bytes]:
        """Fragments of a pre-token between its certain cuts."""
        inside, out, last = self.inside, [], 0
        for i in range(1, len(data)):
            if not inside[data[i - 1]][data[i]]:
                out.append(data[last:i])
                last = i
        out.append(data[last:])
        return out

    def _merge(self, key: tuple[bytes, bool]) -> bytes:
        data, final = key
        parts = [self.letters[b] for b in data]
        if final:
            parts[-1] += self.end
        parts = self._by_heap(parts) if len(parts) > LONG else self._by_scan(parts)
        return array("I", [self.ids[p] for p in parts if p in self.ids]).tobytes()

    def _by_scan(self, parts: list[str]) -> list[str]:
        rank, none = self.rank, (1 << 60, "")
        while len(parts) > 1:
            found = [rank.get(p, none) for p in zip(parts, parts[1:])]
            best = min(found)
            if best is none:
                break
            merged, at, n = [], 0, len(parts)
            while at < n:
                if at + 1 < n and found[at] == best:
                    merged.append(best[1])
                    at += 2
                else:
                    merged.append(parts[at])
                    at += 1
            parts = merged
        return parts

    def _by_heap(self, parts: list[str]) -> list[str]:
        n, rank = len(parts), self.rank
        nxt, prv, live = [*range(1, n), -1], [*range(-1, n - 1)], [True] * n
        heap = [(rank[p][0], i, *p) for i, p in enumerate(zip(parts, parts[1:])) if p in rank]
        heapq.heapify(heap)
        while heap:
            _, i, a, b = heapq.heappop(heap)
            j = nxt[i]
            if not live[i] or j < 0 or parts[i] != a or parts[j] != b:
                continue
            parts[i], live[j], nxt[i] = a + b, False, nxt[j]
            if nxt[j] >= 0:
                prv[nxt[j]] = i
            for x, y in ((prv[i], i), (i, nxt[i])):
                if x >= 0 and y >= 0 and (p := (parts[x], parts[y])) in rank:
                    heapq.heappush(heap, (rank[p][0], x, *p))
        return [p for p, ok in zip(parts, live) if ok]

    def _chunk(self, chunk: str) -> bytes:
        out = []
        for piece in self.pattern.findall(chunk):
            frags = self.forced(piece.encode())
            last = len(frags) - 1
            out += [self.fragments[(f, i == last)] for i, f in enumerate(frags)]
        return b"".join(out)

    def _plain(self, text: str) -> bytes:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text)
            low = "".join(map(str.lower, text)) if "Σ" in text else text.lower()
            chunks = BLANK.split(low) if ODD.search(low) else low.split()
        else:
            low = text.lower()
            chunks = BLANK.split(low) if ODD.search(low) else low.split()
        return b"".join(map(self.chunks.__getitem__, chunks))

    def encode(self, text: str | None) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        if not text:
            return b""
        if self.cut is None or not any(m in text for m in self.mark):
            return self._plain(text)
        return b"".join(array("I", [self.special[s]]).tobytes() if s in self.special else self._plain(s) for s in self.cut.split(text))

    def decode(self, ids: bytes) -> str:
        """The file names no decoder: token strings with spaces between."""
        at = array("I")
        at.frombytes(ids)
        return " ".join(map(self.tokens.__getitem__, at))


_loaded: dict[str, ForcedBoundaryBPE] = {}


def coder(path: str) -> ForcedBoundaryBPE:
    """One coder for each worker process, with its bounded memory of chunks."""
    if path not in _loaded:
        _loaded[path] = c = ForcedBoundaryBPE(path)
        keep(f"bpe {path}", lambda: (c.chunks.clear(), c.fragments.clear()))
    return _loaded[path]


def round_trip(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text", rows: int = 256) -> DataFrame:
    """key, token_ids (packed little-endian unsigned 32-bit ids) and decoded (their text) of every whole text."""
    ship(docs.sparkSession)
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = coder(path)
        forget_others(f"bpe {path}")
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                ids = [c.encode(t) for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.binary()), pa.array([c.decode(i) for i in ids], pa.string())], ["key", "token_ids", "decoded"])

    return docs.select(F.col(key).alias("key"), F.col(text).cast("string")).mapInArrow(run, f"key {kind}, token_ids binary, decoded string").withColumnRenamed("key", key)


def digests(coded: DataFrame, key: str = "doc_id") -> DataFrame:
    return coded.select(key, (F.length("token_ids") / 4).cast("long").alias("n_tokens"), F.sha2("token_ids", 256).alias("ids_sha256"), F.sha2(F.col("decoded").cast("binary"), 256).alias("decoded_sha256"))
