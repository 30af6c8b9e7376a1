"""Suffix-array dedup: a logarithmic family of suffix arrays.

New texts come in batches. Each batch gets a suffix array (its suffixes in lexicographic order, which for matches of at
least LENGTH bytes need be known only to that depth). The batch is merge-scanned against every level of the family: where
a suffix's first LENGTH bytes stand in a level, they have occurred before. What the batch adds becomes a level of its
own, and levels of about equal size merge, so there are O(log n) levels and each suffix is merged O(log n) times.

A corpus is too large for one family, and most of its suffixes have no counterpart. So:

1. A window (LENGTH bytes) has an anchor: the gram of GRAM bytes inside it with the least hash, leftmost among equals. It
   depends on the window's bytes only, so equal windows have equal anchors at equal offsets. Consecutive windows with one
   anchor position form a segment (at most LENGTH - GRAM + 1 of them, all different). Each batch of documents sends the
   shards its distinct (anchor hash, segment hash) pairs, packed, with the first id.
2. A shard sees all segments of an anchor. If all are equal (in 128 bits of hash), the first keeps its bytes and the others
   are repeated wholly. If an anchor has several different segments, they may still share windows: these go, with their
   bytes, to suffix array families, one for each part of the anchors' hash space, in the order of the documents.
3. An anchor with very many different segments (a passage that many documents continue differently) would overload its
   family; its windows are sent singly, by their own hash, each batch sending equal ones once.

Every match is decided for the whole corpus, across and within documents; nothing is sampled. Removal is the union of
repeated windows.

Defined results: null and empty texts have 0 bytes; texts shorter than LENGTH lose nothing; windows are judged on the
input; rows with equal ids count in the order of their texts; null ids come first; what is left after removal need not be
valid UTF-8, so it is offered as binary.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from taskmap.llm.batches import answers, batched, counted, in_order, joined, packed, shard_bounds, unpacked
from taskmap.llm.common import U64, documents, mixed, null_ids, parts_for, relieved

LENGTH, GRAM = 100, 32
#: Different segments of an anchor from which its windows are sent singly: within a batch, and in all.
HOT_IN_BATCH, HOT = 64, 1024
#: Rows that make a batch of a family.
BATCH = 1024
#: Bytes of a text that are hashed at a time.
PIECE = 1 << 17

ONLY, REPEATED, SEVERAL, SINGLY = 0, 1, 2, 3


class SuffixArray:
    """Bytes, and where the suffixes in them begin that count, in lexicographic order by their first `length` bytes.

    Suffixes are compared in words of eight bytes, the last of which overlaps the one before; no suffix is copied.
    """

    def __init__(self, data: np.ndarray, starts: np.ndarray, length: int, lead: np.ndarray | None = None):
        self.data, self.starts = data, starts
        self.offsets = [*range(0, length - 7, 8), *([length - 8] if length % 8 else [])]
        padded = np.concatenate((data, np.zeros(8, np.uint8)))
        self.words = np.ndarray((len(data) + 1,), ">u8", padded, strides=(1,))  # the word at each byte
        self.lead = self.word(starts, 0) if lead is None else lead

    def __len__(self) -> int:
        return len(self.starts)

    def word(self, starts: np.ndarray, k: int) -> np.ndarray:
        return self.words[starts + self.offsets[k]].astype(U64)

    def compare(self, mine: np.ndarray, other: SuffixArray, theirs: np.ndarray) -> np.ndarray:
        """-1, 0 or 1 for each pair of suffixes whose first words are equal: by the first word that differs."""
        sign, at = np.zeros(len(mine), np.int8), np.arange(len(mine))
        for k in range(1, len(self.offsets)):
            a, b = self.word(mine[at], k), other.word(theirs[at], k)
            differ = a != b
            sign[at[differ]] = np.where(a[differ] < b[differ], -1, 1)
            at = at[~differ]
            if not len(at):
                break
        return sign

    def order(self) -> tuple[np.ndarray, np.ndarray]:
        """The lexicographic order of the starts, equal suffixes as they stand, and which suffix differs from the one before:
        word by word, each time only where suffixes are still mixed."""
        order = np.argsort(self.lead, kind="stable")
        lead = self.lead[order]
        new = np.append(True, lead[1:] != lead[:-1])[: len(order)]
        if not len(order):
            return order, new
        group = np.cumsum(new) - 1
        first = np.flatnonzero(new)[group]
        tied = np.flatnonzero(first < np.arange(len(order)))
        apart = self.compare(self.starts[order[tied]], self, self.starts[order[first[tied]]]) != 0
        mixed_groups = np.zeros(group[-1] + 1, bool)
        mixed_groups[group[tied[apart]]] = True
        at = np.flatnonzero(mixed_groups[group])
        for k in range(1, len(self.offsets)):
            if not len(at):
                break
            own = np.cumsum(new[at]) - 1
            at = at[np.bincount(own)[own] > 1]
            some, g = order[at], np.cumsum(new[at]) - 1
            word = self.word(self.starts[some], k)
            by = np.lexsort((word, g))
            order[at], word = some[by], word[by]
            new[at] = np.append(True, (g[1:] != g[:-1]) | (word[1:] != word[:-1]))[: len(at)]
        return order, new

    def only(self, which: np.ndarray) -> SuffixArray:
        return SuffixArray(self.data, self.starts[which], self.offsets[-1] + 8, self.lead[which])

    def scan(self, other: SuffixArray) -> tuple[np.ndarray, np.ndarray]:
        """Of each suffix of another array: its place here, and whether it stands here."""
        low, high = (np.searchsorted(self.lead, other.lead, side) for side in ("left", "right"))
        found = np.zeros(len(other), bool)
        at = np.flatnonzero(low < high)
        while len(at):
            middle = (low[at] + high[at]) // 2
            sign = self.compare(self.starts[middle], other, other.starts[at])
            found[at[sign == 0]] = True
            low[at] = np.where(sign < 0, middle + 1, np.where(sign == 0, middle, low[at]))
            high[at] = np.where(sign < 0, high[at], middle)
            at = at[low[at] < high[at]]
        return low, found

    def merged(self, newer: SuffixArray) -> SuffixArray:
        """Both in one array; no suffix stands in both."""
        place, _ = self.scan(newer)
        starts = np.insert(self.starts, place, newer.starts + len(self.data))
        return SuffixArray(np.concatenate((self.data, newer.data)), starts, self.offsets[-1] + 8, np.insert(self.lead, place, newer.lead))


class SuffixFamily:
    """The levels, each a suffix array of different suffixes, as far as the length that matters."""

    def __init__(self, length: int = LENGTH):
        self.length, self.levels = length, []

    def suffixes(self, texts: list[bytes]) -> SuffixArray:
        """All suffixes of at least the length, text by text."""
        whole = np.frombuffer(b"".join(texts), np.uint8)
        sizes = np.array([len(t) for t in texts], np.int64)
        begins = np.cumsum(sizes) - sizes
        counts = np.maximum(sizes - self.length + 1, 0)
        starts = np.repeat(begins - (np.cumsum(counts) - counts), counts) + np.arange(counts.sum())
        return SuffixArray(whole, starts.astype(np.int64), self.length)

    def add(self, texts: list[bytes]) -> np.ndarray:
        """Adds texts, which follow all earlier ones; True for each suffix whose first bytes began before."""
        own = self.suffixes(texts)
        if not len(own):
            return np.zeros(0, bool)
        order, fresh = own.order()
        distinct = own.only(order[fresh])
        known = np.zeros(len(distinct), bool)
        for level in self.levels:
            known |= level.scan(distinct)[1]
        repeated = np.zeros(len(own), bool)
        repeated[order] = ~fresh | known[np.cumsum(fresh) - 1]
        if not known.all():
            self.levels.append(distinct.only(~known))
        while len(self.levels) > 1 and len(self.levels[-2]) < 2 * len(self.levels[-1]):
            newer, older = self.levels.pop(), self.levels.pop()
            self.levels.append(older.merged(newer))
        return repeated


def _step(a: np.ndarray, b: np.ndarray, k: int) -> np.ndarray:
    """Hashes of strings from those of their two parts; not linear, so no structure of the bytes cancels out."""
    h = a * U64(0x9E3779B97F4A7C15 + 2 * k) + (b ^ (b >> U64(32))) * U64(0xD6E8FEB86659FD93)
    return h ^ (h >> U64(29))


def gram_hashes(data: np.ndarray, lengths: tuple[int, ...]) -> list[np.ndarray]:
    """Hashes of all substrings of each length, from those of powers of two."""
    powers = [mixed(np.arange(1, 257, dtype=U64))[data]]
    while 1 << len(powers) <= max(lengths):
        half = 1 << (len(powers) - 1)
        last = powers[-1]
        powers.append(_step(last[:-half], last[half:], len(powers)) if len(last) > half else np.zeros(0, U64))
    out = []
    for length in lengths:
        own, done = None, 0
        for i in reversed(range(len(powers))):
            if length >> i & 1:
                n = max(0, len(data) - length + 1)
                part = powers[i][done : done + n]
                own = part if own is None else _step(own[:n], part, 64 + i)
                done += 1 << i
        out.append(mixed(own[: max(0, len(data) - length + 1)]))
    return out


def segments(data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Starts and numbers of windows of a text's segments, their anchor hashes and their own."""
    if len(data) > PIECE + LENGTH:
        found, at = [], 0
        while at < len(data) - LENGTH + 1:
            piece = segments(data[at : at + PIECE + LENGTH - 1])
            found.append((piece[0] + at, *piece[1:]))
            at += PIECE
        return tuple(np.concatenate([f[i] for f in found]) for i in range(4))
    n = len(data) - LENGTH + 1
    if n <= 0:
        none = np.zeros(0, np.int64)
        return none, none, none.astype(U64), none.astype(U64)
    grams, whole = gram_hashes(data, (GRAM, LENGTH))
    low = U64((1 << 24) - 1)
    least = (grams & ~low) | np.arange(len(grams), dtype=U64)  # ties: the leftmost
    width, covered = LENGTH - GRAM + 1, 1
    while 2 * covered <= width:
        least = np.minimum(least[:-covered], least[covered:])
        covered *= 2
    if covered < width:
        least = np.minimum(least[: len(least) - (width - covered)], least[width - covered :])
    anchor = (least & low).astype(np.int64)
    starts = np.flatnonzero(np.append(True, anchor[1:] != anchor[:-1]))
    counts = np.diff(np.append(starts, n))
    # first and last window overlap, so both and the number of windows tell the segment's bytes
    own = mixed(_step(whole[starts], whole[starts + counts - 1], 7) + counts.astype(U64))
    return starts, counts, grams[anchor[starts]], np.maximum(own, U64(1))


class Batch:
    """The segments of a batch in the order of the corpus, and its distinct (anchor, segment) pairs.

    What is said of a pair goes for the first segment that has it; the others are repeated. An anchor that is hot within
    the batch stands once, with 0 for its segment.
    """

    def __init__(self, table: pa.Table, hot_in_batch: int):
        self.ids, self.raw, self.rows = in_order(table)
        parts = [segments(np.frombuffer(r, np.uint8)) for r in self.raw]
        self.counts_by_doc = np.array([len(p[0]) for p in parts], np.int64)
        self.doc = np.repeat(np.arange(len(parts)), self.counts_by_doc)
        self.start, self.count, self.anchor, self.segment = (np.concatenate([p[i] for p in parts]) if parts else np.zeros(0, np.int64) for i in range(4))
        order = np.lexsort((self.segment, self.anchor))  # stable: equal pairs stay in the order of the corpus
        a, s = self.anchor[order], self.segment[order]
        fresh = np.append(True, (a[1:] != a[:-1]) | (s[1:] != s[:-1])) if len(a) else np.zeros(0, bool)
        self.first = order[fresh]
        a, s = a[fresh], s[fresh]
        new = np.append(True, a[1:] != a[:-1]) if len(a) else np.zeros(0, bool)
        each = np.diff(np.append(np.flatnonzero(new), len(a)))
        self.hot = np.repeat(each > hot_in_batch, each)
        self.pair = np.cumsum(~self.hot | new) - 1  # the pair that was sent, for each first segment
        sent = ~self.hot | new
        self.sent = (a[sent], np.where(self.hot[sent], U64(0), s[sent]).astype(U64), self.ids[self.doc[self.first[sent]]] if len(a) else np.zeros(0, np.int64))

    def windows(self, i: int) -> np.ndarray:
        """The hashes of a segment's windows."""
        own = np.frombuffer(self.raw[self.doc[i]], np.uint8)[self.start[i] : self.start[i] + self.count[i] + LENGTH - 1]
        return gram_hashes(own, (LENGTH,))[0]

    def said(self, told: pa.Table) -> np.ndarray:
        """Of each segment: ONLY, REPEATED, SEVERAL or SINGLY, given the shards' answers."""
        own = np.full(len(self.start), REPEATED, np.uint8)
        if len(self.first):
            own[self.first] = joined(told)[self.pair]
        return own

    def single(self, said: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Windows to be sent singly, distinct: (hash, segment, offset), each at its first place in the batch; and which
        segments hold windows that repeat earlier ones of the batch."""
        which = np.flatnonzero(said == SINGLY)
        hashes = np.concatenate([self.windows(i) for i in which]) if len(which) else np.zeros(0, U64)
        of = np.repeat(which, self.count[which])
        offset = np.arange(len(of)) - np.repeat(np.cumsum(self.count[which]) - self.count[which], self.count[which])
        return hashes, of, offset


def repeated_bytes(docs: DataFrame, hot_in_batch: int = HOT_IN_BATCH, hot: int = HOT, carry: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, spans (array of start, end in bytes, end excluded), kept (binary), kept_sha256.

    With carry, row besides: a struct of all columns of docs but the text; spans are widened to whole characters.
    """
    n, bits = counted(docs)
    rows = batched(docs, n, carry)
    families = max(parts_for(docs, 4), int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))

    def send(table: pa.Table) -> pa.Table:
        own = Batch(table, hot_in_batch)
        return packed(list(own.sent), shard_bounds(own.sent[0], bits), table.column("batch")[0].as_py(), ["anchors", "segments", "ids"])

    def sort_out(table: pa.Table) -> pa.Table:
        anchors, sizes = unpacked(table, "anchors", "u8")
        own, ids = unpacked(table, "segments", "u8")[0], unpacked(table, "ids", "i8")[0]
        order = np.lexsort((ids, own, anchors))
        a, s = anchors[order], own[order]
        new = np.append(True, a[1:] != a[:-1]) if len(a) else np.zeros(0, bool)
        fresh = new | np.append(True, s[1:] != s[:-1]) if len(a) else new
        of = np.cumsum(new) - 1
        different = np.bincount(of, weights=fresh).astype(np.int64) if len(of) else np.zeros(0, np.int64)
        single = np.bincount(of, weights=s == 0) > 0 if len(of) else np.zeros(0, bool)
        single |= different > hot
        state = np.where(single[of], SINGLY, np.where(~fresh, REPEATED, np.where(different[of] > 1, SEVERAL, ONLY)))
        said = np.zeros(len(a), np.uint8)
        said[order] = state
        return answers(table, said, sizes)

    empty = pa.table([pa.array([], t) for t in (pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.binary())], ["part", "doc_id", "rank", "batch", "bytes"])

    def send_bytes(table: pa.Table, told: pa.Table) -> pa.Table:
        """Segments that may share windows, and single windows, for the families; rank is the number of the window (of
        all windows of the document's text) and of the text among those with one id."""
        if not len(table):
            return empty
        own = Batch(table, hot_in_batch)
        said = own.said(told)
        batch = table.column("batch")[0].as_py()
        some = np.flatnonzero(said == SEVERAL)
        part, doc, start, size = own.anchor[some], own.doc[some], own.start[some], own.count[some] + LENGTH - 1
        hashes, of, offset = own.single(said)
        first = np.unique(hashes, return_index=True)[1]
        part = np.append(part, hashes[first])
        doc = np.append(doc, own.doc[of[first]]) if len(of) else doc
        start = np.append(start, own.start[of[first]] + offset[first]) if len(of) else start
        size = np.append(size, np.full(len(first), LENGTH))
        # high bits chose the shard: low ones choose the family
        part = (mixed(part) % U64(families)).astype(np.int32)
        data = [own.raw[d][s : s + z] for d, s, z in zip(doc.tolist(), start.tolist(), size.tolist())]
        columns = [pa.array(part, pa.int32()), pa.array(own.ids[doc], pa.int64()), pa.array(_place(own)[doc] + start, pa.int64()), pa.array(np.full(len(part), batch, np.int32)), pa.array(data, pa.binary())]
        return pa.table(columns, ["part", "doc_id", "rank", "batch", "bytes"])

    def search(tables):
        """Families over what arrives, in the order of the corpus; answers with the windows that began before."""
        families_here: dict[int, SuffixFamily] = {}
        for batch in tables:
            held = pa.Table.from_batches([batch])
            for at in range(0, len(held), BATCH):
                some = held.slice(at, BATCH)
                parts = some.column("part").to_numpy()
                raw = some.column("bytes").to_pylist()
                flags: list[bytes | None] = [None] * len(raw)
                for part in np.unique(parts):
                    which = np.flatnonzero(parts == part).tolist()
                    family = families_here.setdefault(int(part), SuffixFamily())
                    repeated = family.add([raw[i] for i in which])
                    done = 0
                    for i in which:
                        k = len(raw[i]) - LENGTH + 1
                        mine = repeated[done : done + k]
                        flags[i] = np.packbits(mine).tobytes() if mine.any() else None
                        done += k
                answer = pa.table([some.column("batch"), some.column("doc_id"), some.column("rank"), pa.array(flags, pa.binary())], ["batch", "doc_id", "rank", "flags"])
                yield from answer.filter(answer.column("flags").is_valid()).to_batches()

    def remove(table: pa.Table, told: pa.Table) -> pa.Table:
        out: list[list] = [[] for _ in range(6)]
        if len(table):
            own = Batch(table, hot_in_batch)
            shards = told.filter(told.column("shard").is_valid())
            said = own.said(shards)
            bad = [np.zeros(max(0, len(r) - LENGTH + 1), bool) for r in own.raw]
            for i in np.flatnonzero(said == REPEATED):
                bad[own.doc[i]][own.start[i] : own.start[i] + own.count[i]] = True
            hashes, of, offset = own.single(said)
            group, first, inverse = np.unique(hashes, return_index=True, return_inverse=True)
            begin = np.cumsum([0, *[len(b) for b in bad]])
            flat = np.concatenate(bad) if bad else np.zeros(0, bool)
            at = begin[own.doc[of]] + own.start[of] + offset if len(of) else np.zeros(0, np.int64)
            later = np.ones(len(of), bool)
            later[first] = False
            flat[at[later]] = True
            # what the families found, by id and place
            found = told.filter(told.column("shard").is_null())
            place = {}
            for d, (i, p) in enumerate(zip(own.ids.tolist(), _place(own).tolist())):
                place.setdefault(i, []).append((p, d))
            for i, rank, flags in zip(found.column("doc_id").to_pylist(), found.column("rank").to_pylist(), found.column("flags").to_pylist()):
                p, d = max(x for x in place[i] if x[0] <= rank)
                where = begin[d] + rank - p
                mine = np.unpackbits(np.frombuffer(flags, np.uint8)).astype(bool)[: begin[d + 1] - where]
                flat[where : where + len(mine)] |= mine
            if len(of):  # all equal windows of the batch share what was said of the first
                shared = flat[at[first]][inverse]
                flat[at[shared]] = True
            for d, raw in enumerate(own.raw):
                starts = np.flatnonzero(flat[begin[d] : begin[d + 1]])
                spans = np.zeros((0, 2), np.int64)
                kept = raw
                if len(starts):
                    breaks = np.flatnonzero(np.diff(starts) > LENGTH)
                    spans = np.column_stack((starts[np.append(0, breaks + 1)], starts[np.append(breaks, len(starts) - 1)] + LENGTH))
                    spans = whole_characters(raw, spans) if carry else spans
                    edges = [0, *spans.ravel().tolist(), len(raw)]
                    kept = b"".join(raw[a:b] for a, b in zip(edges[::2], edges[1::2]))
                got = (own.ids[d], len(raw), len(raw) - len(kept), spans.tolist(), kept, hashlib.sha256(kept).hexdigest())
                for column, value in zip(out, got):
                    column.append(value)
        kinds = (pa.int64(), pa.int64(), pa.list_(pa.list_(pa.int64())), pa.binary(), pa.string())
        columns = [null_ids(np.array(out[0], np.int64)), *[pa.array(c, k) for c, k in zip(out[1:], kinds)]]
        names = ["doc_id", "n_bytes", "n_removed", "spans", "kept", "kept_sha256"]
        if carry:
            columns.append(table.column("row").combine_chunks().take(pa.array(own.rows)) if len(table) else table.column("row"))
            names.append("row")
        return pa.table(columns, names)

    sent = rows.groupBy("batch").applyInArrow(lambda t: relieved(send(t)), "shard int, batch int, anchors binary, segments binary, ids binary")
    said = sent.groupBy("shard").applyInArrow(lambda t: relieved(sort_out(t)), "batch int, shard int, flags binary")
    unclear = rows.groupBy("batch").cogroup(said.groupBy("batch")).applyInArrow(lambda t, u: relieved(send_bytes(t, u)), "part int, doc_id long, rank long, batch int, bytes binary")
    ordered = unclear.repartition(families, "part").sortWithinPartitions("doc_id", "rank")
    found = ordered.mapInArrow(search, "batch int, doc_id long, rank long, flags binary")
    none = F.lit(None)
    told = said.select("batch", "shard", "flags", none.cast("long").alias("doc_id"), none.cast("long").alias("rank")).unionByName(found.select("batch", none.cast("int").alias("shard"), "flags", "doc_id", "rank"))
    result = T._parse_datatype_string("doc_id long, n_bytes long, n_removed long, spans array<array<long>>, kept binary, kept_sha256 string")
    if carry:
        result.add(rows.schema["row"])
    return rows.groupBy("batch").cogroup(told.groupBy("batch")).applyInArrow(lambda t, u: relieved(remove(t, u)), result)


def without_repeats(docs: DataFrame) -> DataFrame:
    """docs, all columns, each text without its repeated bytes (a character that loses a byte goes) and n_chars to match.

    A text without repeats stays as it is, null too.
    """
    found = repeated_bytes(docs.withColumn("_no_text", F.col("text").isNull()), carry=True)
    text, changed = F.col("kept").cast("string"), F.col("n_removed") > 0
    columns = []
    for c in docs.columns:
        if c == "text":
            columns.append(F.when(~F.col("row._no_text"), text).cast(docs.schema[c].dataType).alias(c))
        elif c == "n_chars":
            columns.append(F.when(changed, F.length(text)).otherwise(F.col("row.n_chars")).cast(docs.schema[c].dataType).alias(c))
        else:
            columns.append(F.col(f"row.`{c}`").alias(c))
    return found.select(*columns)


def whole_characters(raw: bytes, spans: np.ndarray) -> np.ndarray:
    """The spans, each widened to begin and end between characters of UTF-8."""
    wide = spans.copy()
    for at, step in ((0, -1), (1, 1)):
        for i, x in enumerate(wide[:, at].tolist()):
            while 0 < x < len(raw) and raw[x] & 0xC0 == 0x80:
                x += step
            wide[i, at] = x
    wide[1:, 0] = np.maximum(wide[1:, 0], wide[:-1, 1])
    return wide


def _place(own: Batch) -> np.ndarray:
    """Where each text's windows begin in the order of its id's texts; 0 unless ids are equal."""
    sizes = np.array([len(r) for r in own.raw], np.int64)
    before = np.cumsum(sizes) - sizes
    new = np.append(True, own.ids[1:] != own.ids[:-1]) if len(sizes) else np.zeros(0, bool)
    return before - before[np.maximum.accumulate(np.where(new, np.arange(len(sizes)), 0))] if len(sizes) else before


def op7_suffixes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_bytes(documents(spark, sf_dir)).select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), "kept_sha256")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op7_suffixes": op7_suffixes}
SQL: dict[str, str] = {
    "op7_suffixes": f"""
WITH bytes AS (
    SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
blocks AS (  -- overlapping, as cutting from a long string costs its length
    SELECT doc_id, 1000 * b AS base, substr(h, 2000 * b + 1, 2000 + {2 * LENGTH - 2}) AS h
    FROM (SELECT doc_id, h, unnest(generate_series(0, len(h) // 2000)) AS b FROM bytes)),
starts AS (
    SELECT doc_id, base, h, unnest(generate_series(0, len(h) // 2 - {LENGTH})) AS i FROM blocks),
found AS (
    SELECT doc_id, base + i AS start, row_number() OVER (PARTITION BY substr(h, 2 * i + 1, {2 * LENGTH}) ORDER BY doc_id, base + i) > 1 AS repeated FROM starts),
breaks AS (
    SELECT doc_id, start, coalesce(start - lag(start) OVER (PARTITION BY doc_id ORDER BY start) > {LENGTH}, true) AS fresh FROM found WHERE repeated),
numbered AS (
    SELECT doc_id, start, sum(fresh::INT) OVER (PARTITION BY doc_id ORDER BY start) AS span FROM breaks),
spans AS (
    SELECT doc_id, min(start) AS first, max(start) + {LENGTH} AS behind FROM numbered GROUP BY doc_id, span),
pieces AS (
    SELECT doc_id, coalesce(lag(behind) OVER (PARTITION BY doc_id ORDER BY first), 0) AS first, first AS behind, behind - first AS gone FROM spans
    UNION ALL
    SELECT b.doc_id, coalesce(max(s.behind), 0), len(any_value(b.h)) // 2, NULL FROM bytes b LEFT JOIN spans s USING (doc_id) GROUP BY b.doc_id)
SELECT doc_id, (len(any_value(h)) // 2)::BIGINT AS n_bytes, coalesce(sum(gone), 0)::BIGINT AS n_removed, count(gone)::BIGINT AS n_spans,
       sha256(unhex(string_agg(substr(h, 2 * first + 1, 2 * (behind - first)), '' ORDER BY first))) AS kept_sha256
FROM pieces JOIN bytes USING (doc_id) GROUP BY doc_id""",
}
