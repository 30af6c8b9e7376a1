"""Token counts by dynamic programming shared in a trie.

A text's pre-tokens are its runs without white space, with the mark of a word's start before them. Distinct pre-tokens
go into a trie. Each node holds the best score of any way to cut the path from the root into vocabulary pieces, and the
pieces of that way; a node needs only its ancestors, so a prefix that thousands of words share is computed once, and a
word's count is read off its last node. A piece's score falls with the logarithm of its rank in the public vocabulary, in
fixed-point numbers, so that sums are exact; ties go to fewer pieces. A character that no piece covers counts as many
byte pieces as it has bytes.

One trie serves all texts that a Python worker sees and starts anew at NODES nodes, so memory is bounded; documents are
one mapInArrow over the scan, without a shuffle. Defined results: null and empty texts have no pre-token and count 0;
rows with equal ids are counted each.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from taskmap.llm.common import documents, sliced, text_bytes, texts

VOCABULARY = "piece_bpe_32k.model"
START = "▁"
NODES = 600_000
#: Score of a byte piece: worse than any piece of the vocabulary.
BYTE = -(1 << 24)


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def piece_scores(path: str) -> dict[str, int]:
    """Fixed-point scores of all ordinary pieces."""
    from sentencepiece import SentencePieceProcessor

    model = SentencePieceProcessor(model_file=path)
    usual = [i for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i) or model.is_unused(i))]
    return {model.id_to_piece(i): -round(math.log(rank + 2) * (1 << 16)) for rank, i in enumerate(usual)}


class CountingTrie:
    """Nodes as numbers: the way down by (node, character), the way up, best score and its pieces in lists.

    Pieces lie in a trie of their reversed strings, so that walking up from a node meets exactly those that end there.
    """

    def __init__(self, scores: dict[str, int]):
        self.reversed: dict = {}
        for piece, score in scores.items():
            at = self.reversed
            for char in reversed(piece[1:]):
                at = at.setdefault(char, [None, {}])[1]
            at.setdefault(piece[0], [None, {}])[0] = score
        self.clear()

    def clear(self) -> None:
        self.down: dict[tuple[int, str], int] = {}
        self.best, self.pieces, self.parent, self.char = [0], [0], [0], [""]
        self.counts: dict[bytes, int] = {}

    def count(self, token: str) -> int:
        """Pieces of the best way to cut token; extends the trie where its path is new."""
        down, best, pieces, parent, chars = self.down, self.best, self.pieces, self.parent, self.char
        at = 0
        for char in token:
            below = down.get((at, char))
            if below is None:
                size = len(char.encode())
                top, n = best[at] + BYTE * size, pieces[at] + size
                node, step = at, self.reversed.get(char)
                while step is not None:  # pieces that end here, from the shortest
                    score = step[0]
                    if score is not None:
                        s, m = best[node] + score, pieces[node] + 1
                        if s > top or (s == top and m < n):
                            top, n = s, m
                    if node == 0:
                        break
                    step = step[1].get(chars[node])
                    node = parent[node]
                below = down[at, char] = len(best)
                best.append(top), pieces.append(n), parent.append(at), chars.append(char)
            at = below
        return pieces[at]

    def count_word(self, word: bytes) -> int:
        got = self.counts.get(word)
        if got is None:
            if len(self.best) + len(word) > NODES or len(self.counts) >= NODES // 2:
                self.clear()
            got = self.count(START + word.decode())
            if len(word) <= 256:
                self.counts[word] = got
        return got


_tries: dict[str, CountingTrie] = {}


def worker_trie(path: str) -> CountingTrie:
    if path not in _tries:
        _tries[path] = CountingTrie(piece_scores(path))
    return _tries[path]


def token_counts(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_words, n_tokens."""
    path = path or vocabulary_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trie = worker_trie(path)
        for batch in sliced(batches):
            words = [raw.split() for raw in text_bytes(batch.column("text"))]
            tokens = [sum(map(trie.count_word, w)) for w in words]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([len(w) for w in words], pa.int64()), pa.array(tokens, pa.int64())], ["doc_id", "n_words", "n_tokens"])

    return texts(docs).mapInArrow(run, "doc_id long, n_words long, n_tokens long")


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(documents(spark, sf_dir))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op6_token_counts": op6_token_counts}
SQL: dict[str, str] = {}
