"""Token counts of texts under a unigram model, by a trie of distinct pre-tokens.

A pre-token is a white-space separated word with the word mark in front. Its count is the number of pieces on the path of
the highest score (fewer pieces win ties). Each node of the trie is a prefix and keeps the forward score and piece count
of the best path to it, so a shared prefix is scored once; the node where a pre-token ends holds its count.

The piece list is a file of a public tokenizer, given as a parameter; scores follow the pieces' order (a logarithmic
rank law), as the file itself has only ranks. A character that no piece covers costs one piece for each UTF-8 byte.

Cases: null text counts as no words; an empty table gives an empty table; a word of LONG characters or more is scored by
the same rule without entering the trie or being kept, in memory that doesn't grow with its length; repeated rows give
repeated rows; a null key is a key like any other; other columns are not read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import forget_others, keep, ship

MARK = "▁"
LONG = 256
SCALE = 1_000_000
ODD = regex.compile("[^\\S\\x20\\x09-\\x0D]|[\\x1C-\\x1F]")
WORDS = regex.compile("[^\\x20\\x09-\\x0D]+")


def rank_scores(path: str) -> dict[str, int]:
    """Whole-number scores of the pieces of a file: the scaled logarithm of 1 / (rank + 2), control and byte pieces left out."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    kept = [model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
    return {p: -round(SCALE * math.log(r + 2)) for r, p in enumerate(kept)}


class PrefixTrie:
    def __init__(self, scores: dict[str, int], most: int = 600_000):
        self.scores, self.most = scores, most
        # ends of pieces: a piece's score, or none for what is only the end of longer pieces; other strings end the search to the left
        self.ends: dict[str, int | None] = {p[k:]: None for p in scores for k in range(len(p))} | scores
        self.byte = min(scores.values(), default=0) - SCALE
        self.reach = max(map(len, scores), default=1)
        self.reset()

    def reset(self) -> None:
        self.next: list[dict[str, int] | None] = [None]
        self.best: list[tuple[int, int]] = [(0, 0)]
        self.counts: dict[str, int] = {}

    def _forward(self, path: str, n: int, done: list[tuple[int, int]]) -> tuple[int, int]:
        """Score and negative piece count of the first n letters, from those of their prefixes."""
        width = 1 if path[n - 1] < "\x80" else len(path[n - 1].encode("utf-8", "surrogatepass"))
        score, pieces = done[n - 1]
        top, ends, k = (score + self.byte * width, pieces - width), self.ends, n - 1
        while k >= 0:
            s = ends.get(path[k:n], 1)
            if s == 1:
                break
            if s is not None:
                x = (done[k][0] + s, done[k][1] - 1)
                if x > top:
                    top = x
            k -= 1
        return top

    def _long(self, path: str, stretch: int = 4096) -> int:
        """Piece count of a path of any length: of its prefixes only those that a piece can reach back to are kept."""
        done, at = [(0, 0)], 0
        while True:
            part = path[at : at + stretch + self.reach]
            for n in range(len(done), len(part) + 1):
                done.append(self._forward(part, n, done))
            if at + len(part) == len(path):
                return -done[-1][1]
            drop = len(part) - self.reach
            at, done = at + drop, done[drop:]

    def count(self, word: str) -> int:
        path = MARK + word
        if len(path) > LONG:
            return self._long(path)
        node, done = 0, [(0, 0)]
        for i, c in enumerate(path):
            kids = self.next[node]
            if kids is None:
                kids = self.next[node] = {}
            child = kids.get(c)
            if child is None:
                child = kids[c] = len(self.best)
                self.next.append(None)
                self.best.append(self._forward(path, i + 1, done))
            node = child
            done.append(self.best[node])
        return -done[-1][1]

    def insert(self, distinct: set[str]) -> None:
        """Insert new pre-tokens in sorted order and keep their terminal counts; the trie is emptied at its bound. Long ones don't enter."""
        if len(self.best) > self.most:
            self.reset()
        for w in sorted(distinct):
            if len(w) < LONG:
                self.counts[w] = self.count(w)


_tries: dict[str, PrefixTrie] = {}


def trie(path: str) -> PrefixTrie:
    if path not in _tries:
        _tries[path] = t = PrefixTrie(rank_scores(path))
        keep(f"trie {path}", t.reset)
    return _tries[path]


def split_words(text: str | None) -> list[str]:
    if not text:
        return []
    return WORDS.findall(text) if ODD.search(text) else text.split()


def count_tokens(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text", rows: int = 512) -> DataFrame:
    """key, n_words and n_tokens of every whole text."""
    ship(docs.sparkSession)
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = trie(path)
        forget_others(f"trie {path}")
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                texts = [split_words(x) for x in part.column(1).to_pylist()]
                fresh = set().union(*texts)
                if len(t.best) > t.most:
                    t.reset()
                t.insert(fresh.difference(t.counts))
                far = {w: t.count(w) for w in fresh if len(w) >= LONG}
                get = (t.counts | far).__getitem__ if far else t.counts.__getitem__
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(map(len, texts), pa.int64()), pa.array((sum(map(get, w)) for w in texts), pa.int64())], ["key", "n_words", "n_tokens"])

    return docs.select(F.col(key).alias("key"), F.col(text).cast("string")).mapInArrow(run, f"key {kind}, n_words long, n_tokens long").withColumnRenamed("key", key)
