"""Byte-pair encoding by a priority queue of merge ranks, and its decoding.

A word's symbols form a doubly linked list. Every adjacent pair that the merge table knows waits in a heap under
(rank, position); the smallest is taken, skipped when it is stale (one of its symbols has meanwhile been merged), and
otherwise applied, which offers at most two new pairs. So a word of n symbols costs O(n log n), however long it is.

Decoding concatenates the strings of the vocabulary, with the separator that a tokenizer without a decoder uses.

Documents are independent, so the operator is one mapInArrow over the scan: no shuffle, no state beyond a bounded
cache for each Python worker. Defined results: a null text is the empty text (no ids, the digest of no bytes), rows
with equal ids are encoded one by one, an empty table gives no rows, other columns are ignored.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import re
import struct
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from taskmap.llm.common import documents, sliced, text_bytes, texts

TOKENIZER = "word_bpe_49k.json"
#: Entries that each half of a worker's cache holds at most. A full half becomes the old one, whose own entries go unless they
#: are asked for again; which changes no result.
CACHE = 250_000

#: The file's split, and what it does to lower-case ASCII without white space. Under another split all goes through the library.
SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
ASCII_SPLIT = re.compile(rb"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^a-z0-9]+")


def vocabulary_path(name: str = TOKENIZER) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def byte_letters() -> list[str]:
    """The letter that stands for each byte in a byte-level vocabulary: itself where it prints, else one from 256 on."""
    prints = {*range(33, 127), *range(161, 173), *range(174, 256)}
    others = iter(range(256, 512))
    return [chr(b if b in prints else next(others)) for b in range(256)]


class MergeTable:
    """Ranks of symbol pairs, over integer symbols.

    A pair is one integer (left << 32 | right), and so is an entry of the queue (rank << 40 | position): both are compared and
    hashed at once, and a rank tells its two symbols and what they become.
    """

    def __init__(self, vocab: dict[str, int], merges: Iterable[tuple[str, str]]):
        self.vocab = vocab
        self.ranks: dict[int, int] = {}
        self.made: list[tuple[int, int, int]] = []
        for rank, (a, b) in enumerate(merges):
            self.ranks[vocab[a] << 32 | vocab[b]] = rank
            self.made.append((vocab[a], vocab[b], vocab[a + b]))

    def merge(self, symbols: list[int]) -> list[int]:
        """Apply all merges, always the one of least rank and, among equals, the leftmost."""
        n = len(symbols)
        if n < 2:
            return symbols
        rank_of, made, push, pop = self.ranks.get, self.made, heapq.heappush, heapq.heappop
        queue = []
        left = symbols[0]
        for i in range(1, n):
            right = symbols[i]
            rank = rank_of(left << 32 | right)
            if rank is not None:
                queue.append(rank << 40 | i - 1)
            left = right
        if not queue:
            return symbols
        heapq.heapify(queue)
        symbols = [*symbols, -1]
        after, before = list(range(1, n + 2)), list(range(-1, n))
        while queue:
            top = pop(queue)
            i = top & 0xFFFFFFFFFF
            left, right, joined = made[top >> 40]
            j = after[i]
            if symbols[i] != left or symbols[j] != right:
                continue  # stale: one of the two symbols is no longer there
            symbols[i], symbols[j] = joined, -1
            j = after[i] = after[j]
            if j < n:
                before[j] = i
                rank = rank_of(joined << 32 | symbols[j])
                if rank is not None:
                    push(queue, rank << 40 | i)
            h = before[i]
            if h >= 0:
                rank = rank_of(symbols[h] << 32 | joined)
                if rank is not None:
                    push(queue, rank << 40 | h)
        return [s for s in symbols if s >= 0]


class WordBPE:
    """Encodes and decodes as the tokenizer file says, special tokens found in the raw text included.

    The file's normalizer and pre-tokenizer come from the public tokenizers library, but for runs whose split is plain
    (ASCII, and Latin letters only); the merging is ours.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        with open(path, encoding="utf-8") as f:
            told = json.load(f)
        library = Tokenizer.from_file(path)
        self.normalizer, self.splitter = library.normalizer, library.pre_tokenizer
        model = told["model"]
        self.suffix = model.get("end_of_word_suffix") or ""
        merges = [tuple(m) if isinstance(m, list) else tuple(m.split(" ")) for m in model["merges"]]
        self.table = MergeTable(model["vocab"], merges)
        self.special = {t["content"].encode(): t["id"] for t in told.get("added_tokens", [])}
        strings = {i: s for s, i in model["vocab"].items()} | {i: s.decode() for s, i in self.special.items()}
        self.strings = [strings.get(i, "").encode() for i in range(max(strings) + 1)]
        parts = (told.get("pre_tokenizer") or {}).get("pretokenizers") or [{}]
        self.known_split = parts[0].get("pattern") == {"Regex": SPLIT} and [p["type"] for p in parts] == ["Split", "ByteLevel"]
        letters = byte_letters()
        self.inner = [model["vocab"].get(c) for c in letters]
        self.final = [model["vocab"].get(c + self.suffix) for c in letters]
        self.chunks: dict[str | bytes, bytes] = {}
        self.old: dict[str | bytes, bytes] = {}

    def word(self, word: str | bytes) -> bytes:
        """The ids of one pre-token, of the library's letters or of bytes."""
        if isinstance(word, bytes):
            inner = self.inner
            symbols = [inner[b] for b in word]
            symbols[-1] = self.final[word[-1]]
        else:
            vocab = self.table.vocab
            symbols = [vocab[c] for c in word[:-1]]
            symbols.append(vocab[word[-1] + self.suffix])
        ids = self.table.merge(symbols)
        return struct.pack(f"<{len(ids)}I", *ids)

    def split(self, run: bytes) -> list[str] | list[bytes]:
        """The pre-tokens of a run without ASCII white space."""
        if self.known_split and run.isascii():
            return ASCII_SPLIT.findall(run.lower())
        text = self.normalizer.normalize_str(run.decode())
        if self.known_split and text.isalpha() and max(text) < "\u0250":
            return [text.encode()]
        return [w for w, _ in self.splitter.pre_tokenize_str(text)]

    def kept(self, key: str | bytes, ids: bytes) -> bytes:
        """The ids, which the cache holds from now on if the key is short."""
        if len(key) <= 64:
            if len(self.chunks) >= CACHE:
                self.old, self.chunks = self.chunks, {}
            self.chunks[key] = ids
        return ids

    def token(self, word: str | bytes) -> bytes:
        """The ids of a pre-token among others in a run. One of bytes shares its entry with the run that is this pre-token alone."""
        return self.chunks.get(word) or self.kept(word, self.old.get(word) or self.word(word))

    def chunk(self, chunk: bytes) -> bytes:
        """The ids of a run without ASCII white space, as little-endian 32-bit integers. The normalizer joins nothing across such
        space, and no pre-token crosses it, so runs are independent."""
        ids = self.old.get(chunk)
        if ids is None:
            words = self.split(chunk)
            ids = self.word(chunk) if words == [chunk] else b"".join([self.token(w) for w in words])
        return self.kept(chunk, ids)

    def plain(self, text: bytes) -> bytes:
        """The ids of a text without special tokens. Only a text of ASCII alone may be lower-cased before it is normalized."""
        known, slow = self.chunks.get, self.chunk
        return b"".join([known(r) or slow(r) for r in (text.lower() if text.isascii() else text).split()])

    def encode_bytes(self, text: bytes) -> bytes:
        if b"<|" not in text:
            return self.plain(text)
        out = []
        while text:
            at, name = min(((text.find(s), s) for s in self.special if s in text), default=(-1, b""))
            if at < 0:
                out.append(self.plain(text))
                break
            out += [self.plain(text[:at]), np.array([self.special[name]], "<u4").tobytes()]
            text = text[at + len(name) :]
        return b"".join(out)

    def encode(self, text: str | None) -> list[int]:
        return np.frombuffer(self.encode_bytes((text or "").encode()), "<u4").tolist()

    def decode(self, ids: Iterable[int]) -> str:
        return self.decode_bytes(ids).decode()

    def decode_bytes(self, ids: Iterable[int]) -> bytes:
        """The vocabulary's strings, a space between each two: this tokenizer names no decoder of its own."""
        return b" ".join(map(self.strings.__getitem__, ids))


_loaded: dict[str, WordBPE] = {}


def loaded(path: str) -> WordBPE:
    """One encoder for each Python worker and file."""
    if path not in _loaded:
        _loaded[path] = WordBPE(path)
    return _loaded[path]


def encode_documents(docs: DataFrame, path: str | None = None, ids: bool = True) -> DataFrame:
    """doc_id, ids array<int>, decoded string (both only if ids), n_tokens, ids_sha256, decoded_sha256."""
    path = path or vocabulary_path()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(path)
        for batch in sliced(batches):
            counts, sha, decoded_sha, all_ids, texts_again = [], [], [], [], []
            for raw in text_bytes(batch.column("text")):
                packed = bpe.encode_bytes(raw)
                decoded = bpe.decode_bytes(np.frombuffer(packed, "<u4").tolist())
                counts.append(len(packed) // 4)
                sha.append(hashlib.sha256(packed).hexdigest())
                decoded_sha.append(hashlib.sha256(decoded).hexdigest())
                if ids:
                    all_ids.append(packed)
                    texts_again.append(decoded)
            columns = [batch.column("doc_id"), pa.array(counts, pa.int64()), pa.array(sha, pa.string()), pa.array(decoded_sha, pa.string())]
            names = ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]
            if ids:
                offsets = np.concatenate(([0], np.cumsum(counts, dtype=np.int64))).astype(np.int32)
                values = pa.array(np.frombuffer(b"".join(all_ids), "<u4").astype(np.int32))
                columns += [pa.ListArray.from_arrays(pa.array(offsets), values), pa.array(texts_again, pa.binary()).cast(pa.string())]
                names += ["ids", "decoded"]
            yield pa.RecordBatch.from_arrays(columns, names)

    schema = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids array<int>, decoded string" if ids else "")
    return texts(docs).mapInArrow(run, schema)


def op1_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(documents(spark, sf_dir), ids=False)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op1_bpe": op1_bpe}
SQL: dict[str, str] = {}
