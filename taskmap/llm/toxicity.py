"""Toxicity by compression distance.

Two zstandard dictionaries are trained apart: one on windows of ordinary text, one on windows of toxic text. A window (a
run of one to WINDOW words) that compresses better with the toxic one by several bytes resembles toxic text. A document's
score is a calibrated function of the largest gains among all its windows, so a passage deep in a long document counts as
much as one at its start.

Most windows of a toxic text are as ordinary as any other's, and a dictionary trained on all of them hardly differs from
the ordinary one. So the toxic dictionary learns from the windows that toxic texts hold far more often than ordinary ones
do, with many different words before and behind (counting neighbours, not occurrences, keeps out the windows of texts
that merely have many copies); of a window that holds a shorter one of that kind, the shorter one.

Windows are padded by the same bytes before and behind. The compressor always finds the padding before, so that both
lengths carry equal overhead and the difference is what the window itself saves; matches are not begun within the last
bytes of a block, hence the padding behind. Marks around each window, as around the trainer's samples, become part of a
match only where the whole window is one match. A gain counts if the window's length with the toxic dictionary is at most
a threshold for its length in bytes, calibrated on the windows that the dictionary learnt from: a longer one shares only
fragments. A run of several words is compressed where each of its words occurs in the windows learnt from: any other
cannot be one match.

Thresholds of the score are calibrated crosswise: texts of each of FOLDS parts get their gains from dictionaries trained
on the others, so that a window that merely recurs in the texts learnt from earns no trust.

Fitting reads at most SAMPLE labelled rows (documented bound, whatever the corpus size), in one task; every text is
scored whole. Scoring is one mapInArrow over the scan, without a shuffle. Defined results: null and empty texts have no
window and get the score of zero gains; without labels of both kinds the score is a constant; repeated ids are scored each.
"""

from __future__ import annotations

import math
import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from taskmap.llm.common import U64, documents, mixed, sliced, table, text_bytes, texts
from taskmap.llm.learning import fitted, fold, labelled_sample, logistic, sigmoid

#: Labelled rows learnt from at most: ordinary, toxic.
SAMPLE = (8000, 4000)
#: Words of the longest window.
WINDOW = 5
FOLDS = 3
#: Of a window that the toxic dictionary learns from: the fewest different neighbours on either side (from 2, one more for
#: each TEXTS_PER_NEIGHBOUR toxic texts learnt from, up to 8), its least ratio of frequencies, and the least number of
#: toxic texts that hold it: so many that EVIDENCE nats speak against chance, were it as common in either kind.
LEAST_NEIGHBOURS, MOST_NEIGHBOURS, TEXTS_PER_NEIGHBOUR, RATIO, EVIDENCE = 2, 8, 60, 20, 9.0
#: Bytes of the dictionaries, at most; how often the trainer gets each window.
ORDINARY_BYTES, TOXIC_BYTES, TIMES = 1 << 14, 1 << 16, 6
THRESHOLD = 0.7
BEFORE, BEHIND = b"~0123456789~window~text~", b"~0123456789~"
OPEN, CLOSE = b"\x01\x02", b"\x0e\x0f"
LEVEL, MIN_MATCH = 15, 3
#: Bytes from which windows share a threshold.
LONGEST = 256
CACHE = 300_000

WORDS = re.compile(r"[^\W\d_]+")


def words(text: str) -> list[str]:
    return WORDS.findall(text.lower())


def marked(window: str) -> bytes:
    return OPEN + window.encode() + CLOSE


@dataclass(frozen=True)
class ToxicityModel:
    ordinary: bytes
    toxic: bytes
    #: The words of the windows that the toxic dictionary learnt from, and its longest compressed length by bytes of a window.
    known: frozenset[str]
    longest: tuple[int, ...]
    weights: tuple[float, ...] = (0.0, 0.0, 0.0, 0.0)
    #: Words of the longest window learnt from.
    most: int = 1

    def lengths(self) -> Callable[[str], tuple[int, int]]:
        """The compressed lengths of a window with the ordinary and with the toxic dictionary."""
        import zstandard as zstd

        def compressor(content: bytes) -> zstd.ZstdCompressor:
            told = zstd.ZstdCompressionParameters.from_level(LEVEL, min_match=MIN_MATCH, window_log=17, write_content_size=False, write_checksum=False, write_dict_id=False)
            # as raw content: with the trainer's entropy tables the two would not code equal rests in equal lengths
            own = zstd.ZstdCompressionDict(content + BEFORE, dict_type=zstd.DICT_TYPE_RAWCONTENT)
            own.precompute_compress(compression_params=told)
            return zstd.ZstdCompressor(compression_params=told, dict_data=own)

        plain, toxic = compressor(self.ordinary).compress, compressor(self.toxic).compress

        def both(window: str) -> tuple[int, int]:
            padded = BEFORE + marked(window) + BEHIND
            return len(plain(padded)), len(toxic(padded))

        return both

    def gains(self) -> Callable[[str], int]:
        """The bytes that a window saves with the toxic dictionary, by a function with a bounded cache."""
        lengths, longest = self.lengths(), self.longest
        cache: dict[str, int] = {}

        def gain(window: str) -> int:
            got = cache.get(window)
            if got is None:
                ordinary, toxic = lengths(window)
                got = ordinary - toxic if toxic <= longest[min(len(window.encode()), LONGEST)] else 0
                if len(cache) >= CACHE:
                    cache.clear()
                if len(window) <= 64:
                    cache[window] = got
            return got

        return gain

    def windows(self, text: str) -> Iterator[str]:
        """All words, and the runs of up to most words that are all known."""
        w = words(text)
        yield from w
        if self.most > 1 and not self.known.isdisjoint(w):
            run: list[str] = []
            for word in w:
                run = [*run[1 - self.most :], word] if word in self.known else []
                for n in range(2, len(run) + 1):
                    yield " ".join(run[-n:])

    def features(self, text: str, gain: Callable[[str], int]) -> tuple[int, int, int]:
        """The largest gain of a window, the sum of the two largest, and of the four largest."""
        top = [0, 0, 0, 0]
        for got in map(gain, self.windows(text)):
            if got > top[3]:
                top[3] = got
                top.sort(reverse=True)
        return top[0], top[0] + top[1], sum(top)

    def score(self, features: np.ndarray) -> np.ndarray:
        return sigmoid(features @ np.array(self.weights[:-1]) + self.weights[-1])


@dataclass
class Words:
    """Texts as numbers of words, one after another, with the text of each; names are the words by number."""

    number: np.ndarray
    text: np.ndarray
    names: list[str]

    @staticmethod
    def of(split: list[list[str]]) -> Words:
        ids: dict[str, int] = {}
        number = np.array([ids.setdefault(x, len(ids)) for w in split for x in w], np.int64)
        return Words(number, np.repeat(np.arange(len(split)), [len(w) for w in split]), list(ids))

    def some(self, texts: np.ndarray) -> Words:
        """Of the texts for which texts is true."""
        which = texts[self.text]
        return Words(self.number[which], self.text[which], self.names)

    def runs(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        """Where runs of n words of one text begin, and their hashes."""
        at = np.arange(max(0, len(self.number) - n + 1))
        at = at[self.text[at] == self.text[at + n - 1]]
        h = np.zeros(len(at), U64)
        for i in range(n):
            h = mixed(h * U64(0x9E3779B97F4A7C15) + self.number[at + i].astype(U64))
        return at, h

    def beside(self, at: np.ndarray, step: int) -> np.ndarray:
        """The words step away from places; -1 where the text ends."""
        to = at + step
        inside = (to >= 0) & (to < len(self.number))
        to = np.where(inside, to, 0)
        return np.where(inside & (self.text[to] == self.text[at]), self.number[to], -1) if len(at) else np.zeros(0, np.int64)


def _different(value: np.ndarray, h: np.ndarray, other: np.ndarray) -> np.ndarray:
    """How many different others go with each value among the hashes h; value ascends."""
    order = np.lexsort((other, h))
    own, other = h[order], other[order]
    new = np.append(True, (own[1:] != own[:-1]) | (other[1:] != other[:-1]))[: len(own)]
    return np.bincount(np.searchsorted(value, own[new]), minlength=len(value))


def telling(held: Words, label: np.ndarray, use: np.ndarray, most: int = WINDOW) -> list[str]:
    """The windows of toxic texts, of those to use, that tell them from ordinary ones; none holds another."""
    sizes = [int((use & (label == k)).sum()) for k in (0, 1)]
    least = min(MOST_NEIGHBOURS, max(LEAST_NEIGHBOURS, sizes[1] // TEXTS_PER_NEIGHBOUR))
    enough = EVIDENCE / max(0.5, -math.log((sizes[1] + 1) / (sum(sizes) + 2)))
    rare = RATIO * max(sizes[1], 1) / max(sizes[0], 1)
    usual, toxic = (held.some(use & (label == k)) for k in (0, 1))
    found: list[str] = []
    for n in range(1, most + 1):
        at, h = toxic.runs(n)
        value, count = np.unique(h, return_counts=True)
        value = value[count >= enough]

        def narrowed(keep: np.ndarray) -> None:
            nonlocal value, at, h
            value = value[keep]
            some = np.isin(h, value)
            at, h = at[some], h[some]

        narrowed(np.ones(len(value), bool))
        for step in (-1, n):
            narrowed(_different(value, h, toxic.beside(at, step)) >= least)
        count = _different(value, h, toxic.text[at])
        there, own = usual.runs(n)
        some = np.isin(own, value)
        common = _different(value, own[some], usual.text[there[some]])
        narrowed((count >= enough) & (count > rare * (common + 0.5)))
        first = at[np.unique(h, return_index=True)[1]]
        new = sorted(" ".join(toxic.names[k] for k in toxic.number[i : i + n]) for i in first)
        found += [x for x in new if not any(f" {short} " in f" {x} " for short in found)]
    return found


def trained(windows: list[bytes], most: int) -> bytes:
    """A dictionary by the library's trainer; of too few windows to train on, the windows themselves."""
    import zstandard as zstd

    try:
        return zstd.train_dictionary(most, windows, k=128, d=8).as_bytes()
    except zstd.ZstdError:
        return b"".join(dict.fromkeys(windows))[-most:]


def dictionaries(held: Words, label: np.ndarray, use: np.ndarray, window: int = WINDOW) -> ToxicityModel:
    """Both dictionaries, of the texts to use, and how long a window learnt from may be with the toxic one."""
    rng = np.random.default_rng(5)  # an order for the trainer, the same in each run
    ordinary = held.some(use & (label == 0)).number
    usual = [marked(held.names[i]) for i in rng.permutation(ordinary)[: 5 * ORDINARY_BYTES]]
    chosen = telling(held, label, use, window)
    told = [marked(x) for x in chosen for _ in range(TIMES)]
    told = [told[i] for i in rng.permutation(len(told))]
    size = min(TOXIC_BYTES, max(1024, 2 * sum(len(marked(x)) for x in chosen)))
    model = ToxicityModel(trained(usual, ORDINARY_BYTES), trained(told, size), frozenset(x for w in chosen for x in w.split()), (0,) * (LONGEST + 1), most=max([1, *(len(x.split()) for x in chosen)]))
    lengths = model.lengths()
    longest, got = [], []
    by_size: dict[int, list[int]] = {}
    for x in chosen:
        by_size.setdefault(min(LONGEST, len(x.encode())), []).append(lengths(x)[1])
    for n in range(LONGEST + 1):
        got = sorted(got + by_size.get(n, []))
        longest.append(got[len(got) * 9 // 10] if got else 0)
    return replace(model, longest=tuple(longest))


def measured(model: ToxicityModel, sample: list[tuple[int, str]]) -> np.ndarray:
    gain = model.gains()
    return np.array([model.features(text, gain) for _, text in sample], float).reshape(-1, 3)


def fit(sample: list[tuple[int, str]], window: int = WINDOW) -> ToxicityModel:
    """Dictionaries from the sample, thresholds calibrated crosswise."""
    held = Words.of([words(text) for _, text in sample])
    label, part = np.array([y for y, _ in sample], np.int64), np.arange(len(sample)) % FOLDS
    x = np.zeros((len(sample), 3))
    for k in range(FOLDS):
        x[k::FOLDS] = measured(dictionaries(held, label, part != k, window), sample[k::FOLDS])
    weights = logistic(x, label.astype(float), ridge=0.05)
    return replace(dictionaries(held, label, part >= 0, window), weights=tuple(weights.tolist()))


def score_documents(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """doc_id, gain (the largest of a window, in bytes), score, predicted."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gain = model.gains()
        for batch in sliced(batches):
            x = np.array([model.features(raw.decode(), gain) for raw in text_bytes(batch.column("text"))], float).reshape(-1, 3)
            score = model.score(x)
            columns = [batch.column("doc_id"), pa.array(x[:, 0].astype(np.int32)), pa.array(score), pa.array((score >= THRESHOLD).astype(np.int32))]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "gain", "score", "predicted"])

    return texts(docs).mapInArrow(run, "doc_id long, gain int, score double, predicted int")


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = fitted(labelled_sample(docs, table(spark, sf_dir, "labels"), "toxic", fold(F.col("doc_id"), 3) != 1, SAMPLE), fit)
    held_out = F.coalesce(fold(F.col("doc_id"), 3) == 1, F.lit(False))
    return score_documents(docs, model).select("doc_id", held_out.alias("held_out"), "score", "predicted", "gain")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op3_toxicity": op3_toxicity}
SQL: dict[str, str] = {}
