"""N-gram Jaccard join by parity sketches.

A document's set holds its distinct shingles of GRAM words. Each shingle flips one bit of a sketch, so the Hamming
distance of two sketches is at most the size of the sets' symmetric difference. Sets fall into bands by size, and partners
lie in the same or neighbouring bands; in a band the difference of two partners is at most D. A sketch is cut into pieces,
so many that usually more than D of them are not zero. A piece has 2^64 bits, of which hardly any are set; it is held as
the XOR of the hashes of its odd bits, which differs where the bits do. At most D pieces differ between partners, so of
any D + 1 pieces one is equal (pigeonhole); and as in prefix filters it is enough that both send the first D + 1 of their
pieces that are not zero, in one order for all. Here that order is by the number of sets that have the piece, rarest first:
a passage that many documents share, or a set's place in a crowd that it differs from, then hardly brings anyone together.
Sets with fewer pieces that are not zero send all, zero ones last. Documents that share a piece are candidates, and the
sets themselves decide: a pair links when its Jaccard similarity is at least the threshold.

The join returns classes of links, not pairs, and never forms all pairs of a group that shares a piece:

1. Equal sets count as one. All pieces of a batch of documents go to shards, packed, and shards tell how many sets have
   each of those that meet another one; the rest have no partner. So a set's first D + 1 are known.
2. Each group that shares a piece has a head: the member with most common pieces. Members are tied to it; a short sketch
   of each set (two bits for each shingle, about) drops ties whose Hamming distance already passes what a link may differ
   by. The others are verified with whole sets, which meet in tasks of at most SALT sets, and the links' components formed.
3. Only groups that still hold several components can hide a link. In these, members outside the head's component meet
   all others, in blocks, by their short sketches; pairs of different components that a link may join are verified as
   before. Pairs within a component need no check. After that no link between components is left.

Defined results: null texts and texts without words have no shingle, link with nothing and are their own component; with
fewer words than GRAM the whole sequence is the one shingle; rows with equal ids are separate documents in the order of
their texts (component_id can be equal to another row's id all the same); null ids come first and give a null component.
"""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from taskmap.llm.batches import WordHashes, batched, counted, in_order, packed, shard_bounds, unpacked
from taskmap.llm.common import NULL_ID, U64, documents, ensure_checkpoints, mixed, relieved, stored
from taskmap.llm.components import components

GRAM, PERCENT = 3, 90
#: Sets that meet in a task; members of a block.
SALT, BLOCK = 256, 1024
#: Bits of a short sketch for each shingle, about.
BITS_EACH = 2

LOWER = bytes.maketrans(bytes(range(65, 91)), bytes(range(97, 123)))
PIECE, DOCUMENT = 0, 1
ABOVE, ZERO = 1, 2
#: The place in the order of pieces that are zero.
LAST = 1 << 20

_hashes = WordHashes()


def shingles(text: bytes, gram: int) -> np.ndarray:
    """The ascending hashes of a text's distinct shingles."""
    words = text.translate(LOWER).split()
    if not words:
        return np.zeros(0, U64)
    h = _hashes.of(words)
    n = max(1, len(h) - gram + 1)
    own = np.full(n, len(h) if len(h) < gram else gram, U64)
    for i in range(min(gram, len(h))):
        own = mixed(own * U64(0x9E3779B97F4A7C15) + h[i : i + n])
    return np.unique(own)


class Bands:
    """Sizes where bands begin, and what follows from the threshold."""

    def __init__(self, percent: int):
        self.percent = percent
        edges = [1]
        while edges[-1] < 1 << 40:
            edges.append(max(edges[-1] + 1, -(-edges[-1] * 100 // percent)))
        self.edges = np.array(edges, np.int64)

    def of(self, size: int) -> int:
        return int(np.searchsorted(self.edges, size, side="right")) - 1

    def difference(self, total: int) -> int:
        """The largest symmetric difference of linked sets with so many elements together."""
        return total * (100 - self.percent) // (100 + self.percent)

    def most(self, band: int) -> int:
        """D: the largest difference of partners of which the larger one is in the band."""
        return self.difference(2 * (int(self.edges[band + 1]) - 1))

    def pieces(self, band: int) -> int:
        """So many that the smallest partner is expected to leave a fifth more than D of them not zero, within limits."""
        need = self.most(band) + 1
        least = int(self.edges[max(0, band - 1)])
        n = need
        while n < 1.7 * need and n * -math.expm1(-least / n) < 1.2 * need + 2 * math.sqrt(n * math.exp(-least / n)):
            n += max(1, need // 64)
        return n

    def words(self, band: int) -> int:
        """Of a short sketch."""
        return -(-int(self.edges[band + 1]) * BITS_EACH // 64)

    def short(self, own: np.ndarray, band: int) -> np.ndarray:
        """A parity sketch of a few bits for each shingle, as words of 64 bits: a filter."""
        n = self.words(band)
        at = ((own & U64(0xFFFFFFFF)) * U64(n)) >> U64(32)
        words = np.zeros(n, U64)
        np.bitwise_xor.at(words, at.astype(np.int64), U64(1) << ((own >> U64(40)) & U64(63)))
        return words

    def sketch(self, own: np.ndarray, band: int) -> np.ndarray:
        """The parity sketch of a set: for each of the band's pieces the XOR of its odd bits' hashes."""
        n = self.pieces(band)
        piece = ((own >> U64(32)) * U64(n)) >> U64(32)  # ascends as the hashes do
        starts = np.searchsorted(piece, np.arange(n, dtype=U64))
        some = np.flatnonzero(np.diff(np.append(starts, len(own))))
        words = np.zeros(n, U64)
        if len(some):
            words[some] = np.bitwise_xor.reduceat(mixed(own), starts[some])
        return words

    def keys(self, sketch: np.ndarray, band: int) -> np.ndarray:
        return mixed(mixed(sketch) + np.arange(len(sketch), dtype=U64) * U64(0xC2B2AE3D27D4EB4F) + U64((band + 1) * 0x9E3779B97F4A7C15 & (1 << 64) - 1))

    def sent(self, own: np.ndarray, band: int) -> tuple[np.ndarray, np.ndarray, int]:
        """Keys of the pieces that a set sends for a band, which of them are zero, and how many more of them than it sends
        count for the pigeonhole (negative: it sends more than D + 1)."""
        sketch, need = self.sketch(own, band), self.most(band) + 1
        keys, zero = self.keys(sketch, band), sketch == 0
        if len(sketch) - int(zero.sum()) >= need:
            keys, zero = keys[~zero], zero[~zero]
        return keys, zero, need - len(keys)

    def linked(self, shared: int, a: int, b: int) -> bool:
        return 100 * shared >= self.percent * (a + b - shared)


class Batch:
    """The texts of a batch in the order of the corpus, with their sets as they are asked for."""

    def __init__(self, table: pa.Table, gram: int):
        self.number, self.gram = table.column("batch")[0].as_py(), gram
        self.ids, self.raw, _ = in_order(table)

    def set(self, row: int) -> np.ndarray:
        return shingles(self.raw[row], self.gram)

    def nodes(self, sets: list[np.ndarray]) -> np.ndarray:
        """For each row the first row with the same set; rows without shingles stand alone."""
        first: dict[bytes, int] = {}
        return np.array([first.setdefault(s.tobytes(), i) if len(s) else i for i, s in enumerate(sets)], np.int64)


def node_of(batch: int, row: np.ndarray | int) -> np.ndarray | int:
    return (batch << 32) + row


DOCUMENTS = "doc_id long, first long, size long, digest binary, spare_home int, spare_above int, home array<long>, above array<long>"
#: Rows of the first step: a DOCUMENT, or a PIECE (key, tag and place in the order) of a node.
FOUND = f"kind int, node long, key long, tag int, place int, {DOCUMENTS}"
_KINDS = [pa.int32(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.binary(), pa.int32(), pa.int32(), pa.list_(pa.int64()), pa.list_(pa.int64())]
_NAMES = [x.split()[0] for x in FOUND.split(", ")]


def _found(kind: int, n: int, **columns: np.ndarray | list) -> pa.Table:
    """Rows of FOUND; columns that aren't given are null."""
    own = columns | {"kind": np.full(n, kind)}
    return pa.table([pa.array(own[c], k) if c in own else pa.nulls(n, k) for c, k in zip(_NAMES, _KINDS)], _NAMES)


class Join:
    """The operator with its parameters; similar() and its steps."""

    def __init__(self, docs: DataFrame, gram: int = GRAM, percent: int = PERCENT):
        self.spark = docs.sparkSession
        self.n, self.bits = counted(docs)
        self.rows = batched(docs, self.n)
        self.gram, self.bands = gram, Bands(percent)
        ensure_checkpoints(self.spark)

    def first_step(self) -> DataFrame:
        """Rows of FOUND: the documents, and the pieces that may bring one together with others."""
        gram, bands, bits = self.gram, self.bands, self.bits

        def send(table: pa.Table) -> pa.Table:
            import xxhash

            own = Batch(table, gram)
            sets = [own.set(i) for i in range(len(own.raw))]
            first = own.nodes(sets)
            keys, rows = [np.zeros(0, U64)], [np.zeros(0, np.uint32)]
            spare: tuple[list, list] = ([], [])
            shorts: tuple[list, list] = ([], [])
            digests: list[bytes | None] = []
            for i, s in enumerate(sets):
                alone = first[i] == i and len(s) > 0
                digests.append(xxhash.xxh3_128_digest(s.tobytes()) if alone else None)
                for above in (0, 1):
                    band = bands.of(len(s)) + above if alone else 0
                    some, zero, more = bands.sent(s, band) if alone else (keys[0], None, None)
                    if alone:
                        keys.append(some)
                        rows.append(4 * i + ZERO * zero.astype(np.uint32) + above)
                    spare[above].append(more)
                    shorts[above].append(bands.short(s, band).view(np.int64) if alone else None)
            all_keys, all_rows = np.concatenate(keys), np.concatenate(rows).astype(np.uint16 if 4 * len(sets) <= 1 << 16 else np.uint32)
            order = np.argsort(all_keys, kind="stable")
            all_keys = all_keys[order]
            tail = ((all_keys >> U64(32 - bits)) & U64(0xFFFFFFFF)).astype(np.uint32)  # what follows the shard's bits
            out = packed([tail, all_rows[order]], shard_bounds(all_keys, bits), own.number, ["keys", "rows"])
            # the documents themselves go to a shard of their own, numbered by the batch
            n = len(sets)
            told = _found(DOCUMENT, n, node=node_of(own.number, np.arange(n)), doc_id=own.ids, first=node_of(own.number, first), size=np.array([len(s) for s in sets], np.int64), digest=digests, spare_home=spare[0], spare_above=spare[1], home=shorts[0], above=shorts[1])
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, told.schema) as stream:
                stream.write_table(told)
            mine = [pa.array([-1 - own.number], pa.int32()), pa.array([own.number], pa.int32()), pa.array([sink.getvalue().to_pybytes()], pa.binary()), pa.array([b""], pa.binary())]
            return pa.concat_tables([out, pa.table(mine, out.column_names)])

        def meet(table: pa.Table) -> pa.Table:
            shard = table.column("shard")[0].as_py()
            if shard < 0:
                return pa.concat_tables([pa.ipc.open_stream(x).read_all() for x in table.column("keys").to_pylist()])
            keys, sizes = unpacked(table, "keys", "u4")
            widths = [4 * len(r) // len(k) for k, r in zip(table.column("keys").to_pylist(), table.column("rows").to_pylist())]
            rows = np.concatenate([np.frombuffer(x, f"u{w}").astype(np.uint32) for x, w in zip(table.column("rows").to_pylist(), widths)])
            order = np.argsort(keys, kind="stable")
            k = keys[order]
            starts = np.flatnonzero(np.append(True, k[1:] != k[:-1]))
            counts = np.diff(np.append(starts, len(k)))
            # members that are all from the band below meet under that band's keys
            useful = (counts > 1) & (np.minimum.reduceat(rows[order] & ABOVE, starts) == 0)
            place = np.ceil(np.log2(counts) * 8).astype(np.int32)
            often = np.repeat(useful, counts)
            some = order[often]
            tag = (rows[some] & 3).astype(np.int32)
            node = (np.repeat(table.column("batch").to_numpy().astype(np.int64), sizes)[some] << 32) + (rows[some] >> 2)
            return _found(PIECE, len(some), node=node, key=(shard << 32) + k[often].astype(np.int64), tag=tag, place=np.where(tag & ZERO, LAST, np.repeat(place, counts)[often]))

        sent = self.rows.groupBy("batch").applyInArrow(lambda t: relieved(send(t)), "shard int, batch int, keys binary, rows binary")
        return sent.groupBy("shard").applyInArrow(lambda t: relieved(meet(t)), FOUND)

    def members(self, pieces: DataFrame, nodes: DataFrame) -> DataFrame:
        """key, node, upper (whether the key is of the band above the node's), size, common: of each node the pieces among
        its first D + 1 that it may share; common is their number."""
        own = pieces.select("key", "node", "place", F.col("tag").bitwiseAND(F.lit(ABOVE)).alias("upper"))
        own = own.join(nodes.select("node", "size", "spare_home", "spare_above"), "node")
        group = W.partitionBy("node", "upper")
        # pieces that nobody shares come first in the order and take their places
        left = F.when(F.col("upper") == 1, F.col("spare_above")).otherwise(F.col("spare_home")) + F.count("*").over(group)
        own = own.withColumns({"common": left, "nth": F.row_number().over(group.orderBy("place", "key"))})
        return own.filter(F.col("nth") <= F.col("common")).select("key", "node", "upper", "size", "common")

    def ties(self, members: DataFrame) -> DataFrame:
        """Distinct pairs a (head), b (member) of groups that share a key, where sizes allow a link."""
        head = F.max_by(F.struct("node", "size"), F.struct("common", "node")).alias("head")
        heads = members.groupBy("key").agg(head, F.min("upper").alias("least"), F.min("node").alias("x"), F.max("node").alias("y"))
        both = members.join(heads.filter("least = 0 AND x <> y").select("key", "head"), "key").filter("node <> head.node")
        small, large = F.least("size", "head.size"), F.greatest("size", "head.size")
        return both.filter(100 * small >= self.bands.percent * large).select(F.col("head.node").alias("a"), F.col("node").alias("b")).distinct()

    def possible(self, pairs: DataFrame, nodes: DataFrame) -> DataFrame:
        """Of pairs(a, b), those that sizes and short sketches allow to link."""
        narrow = lambda x: nodes.select(F.col("node").alias(x), F.col("size").alias(f"size_{x}"), F.col("home").alias(f"home_{x}"), F.col("above").alias(f"above_{x}"))
        both = pairs.join(narrow("a"), "a").join(narrow("b"), "b")
        most = F.call_function("div", (F.col("size_a") + F.col("size_b")) * (100 - self.bands.percent), F.lit(100 + self.bands.percent))
        # both as sketches for the larger one's band: its words tell which that is
        words = {x: F.size(f"home_{x}") for x in "ab"}
        short = {x: F.when(words[x] < words[y], F.col(f"above_{x}")).otherwise(F.col(f"home_{x}")) for x, y in ("ab", "ba")}
        flips = F.zip_with(short["a"], short["b"], lambda x, y: F.bit_count(x.bitwiseXOR(y)))
        near = F.aggregate(flips, F.lit(0), lambda s, x: s + x) <= most
        return both.filter((F.size(short["a"]) == F.size(short["b"])) & near).select("a", "b")

    def verified(self, pairs: DataFrame) -> DataFrame:
        """Of pairs(a, b), those whose sets are similar enough. Sets of b meet that of a in tasks of about SALT."""
        gram, bands = self.gram, self.bands
        crowd = pairs.groupBy("a").agg(F.ceil(F.count("*") / SALT).cast("int").alias("tasks"))
        salt = F.pmod(F.xxhash64("b"), F.col("tasks")).cast("int")
        members = pairs.join(crowd, "a").select("a", salt.alias("salt"), F.col("b").alias("node"))
        firsts = members.select("a", "salt").distinct().select("a", "salt", F.col("a").alias("node"))
        asked = members.unionByName(firsts).withColumn("batch", F.shiftright("node", 32).cast("int"))

        def send(table: pa.Table, asked: pa.Table) -> pa.Table:
            names = ["a", "salt", "node", "set"]
            if not len(table) or not len(asked):
                return pa.table([pa.array([], t) for t in (pa.int64(), pa.int32(), pa.int64(), pa.binary())], names)
            own = Batch(table, gram)
            rows = (asked.column("node").to_numpy() & 0xFFFFFFFF).tolist()
            known = {i: own.set(i).tobytes() for i in set(rows)}
            return pa.table([asked.column("a"), asked.column("salt"), asked.column("node"), pa.array([known[i] for i in rows], pa.binary())], names)

        def check(key: tuple, table: pa.Table) -> pa.Table:
            a = key[0].as_py()
            nodes = table.column("node").to_pylist()
            sets = table.column("set").to_pylist()
            first = np.frombuffer(sets[nodes.index(a)], U64)
            good = []
            for node, raw in zip(nodes, sets):
                own = np.frombuffer(raw, U64)
                if node != a:
                    at = np.searchsorted(first, own)
                    at[at == len(first)] = 0
                    if bands.linked(int((first[at] == own).sum()), len(first), len(own)):
                        good.append(node)
            return pa.table([pa.array([a] * len(good), pa.int64()), pa.array(good, pa.int64())], ["a", "b"])

        sent = self.rows.groupBy("batch").cogroup(asked.groupBy("batch")).applyInArrow(lambda t, u: relieved(send(t, u)), "a long, salt int, node long, set binary")
        return sent.groupBy("a", "salt").applyInArrow(check, "a long, b long")

    def hidden(self, members: DataFrame, nodes: DataFrame, labels: DataFrame) -> DataFrame:
        """Pairs of different components that their short sketches allow to link, from groups of several components."""
        bands = self.bands
        own = members.join(labels, "node", "left").withColumn("component", F.coalesce("component", "node"))
        major = F.max_by("component", F.struct("common", "node")).alias("major")
        groups = own.groupBy("key").agg(major, F.min("component").alias("x"), F.max("component").alias("y"), F.count("*").alias("m"), F.min("upper").alias("least"))
        groups = groups.filter("x <> y AND least = 0").select("key", "major", F.ceil(F.col("m") / BLOCK).cast("int").alias("blocks"))
        told = own.join(groups, "key")
        minor = F.col("component") != F.col("major")
        home = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
        told = told.select("key", "node", "upper", "component", minor.alias("minor"), home.alias("home_block"), F.explode(F.when(minor, F.sequence(F.lit(0), F.col("blocks") - 1)).otherwise(F.array(home))).alias("block"))
        short = F.when(F.col("upper") == 1, F.col("above")).otherwise(F.col("home"))
        told = told.join(nodes, "node").select("key", "block", "node", "component", "upper", "minor", (F.col("block") == F.col("home_block")).alias("at_home"), "size", short.alias("short"))

        def compare(table: pa.Table) -> pa.Table:
            """Many groups at once: rows lie group by group, and pairs at each distance within a group are compared together."""
            table = table.sort_by([("key", "ascending"), ("block", "ascending")])
            lists = table.column("short").combine_chunks()
            words, lengths = lists.flatten().to_numpy().view(U64), np.diff(lists.offsets.to_numpy())
            starts = np.cumsum(lengths) - lengths
            minor, at_home = (table.column(c).to_numpy(zero_copy_only=False) for c in ("minor", "at_home"))
            key, block, size, component, node, upper = (table.column(c).to_numpy() for c in ("key", "block", "size", "component", "node", "upper"))
            left, right = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            at = np.arange(len(key))
            step = 0
            while len(at):
                step += 1
                at = at[at + step < len(key)]
                at = at[(key[at] == key[at + step]) & (block[at] == block[at + step])]
                i, j = at, at + step
                small, large = np.minimum(size[i], size[j]), np.maximum(size[i], size[j])
                near = (component[i] != component[j]) & (minor[i] | minor[j]) & (at_home[i] | at_home[j]) & (upper[i] + upper[j] < 2) & (100 * small >= bands.percent * large)
                i, j = i[near], j[near]
                most = (size[i] + size[j]) * (100 - bands.percent) // (100 + bands.percent)
                for n in np.unique(lengths[i]):
                    some = (lengths[i] == n) & (lengths[j] == n)  # a group's sketches have one length, unless its key is of two bands by chance
                    span = np.arange(n)
                    apart = np.bitwise_count(words[starts[i[some]][:, None] + span] ^ words[starts[j[some]][:, None] + span]).sum(1, dtype=np.int64)
                    good = apart <= most[some]
                    left.append(np.minimum(node[i[some][good]], node[j[some][good]]))
                    right.append(np.maximum(node[i[some][good]], node[j[some][good]]))
            a, b = np.concatenate(left), np.concatenate(right)
            order = np.lexsort((b, a))
            a, b = a[order], b[order]
            new = np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1]))[: len(a)]
            return pa.table([pa.array(a[new]), pa.array(b[new])], ["a", "b"])

        # whole groups meet in buckets, as most are tiny
        bucket = F.pmod(F.xxhash64("key", "block"), F.lit(16 * self.n)).cast("int")
        found = told.withColumn("bucket", bucket).groupBy("bucket").applyInArrow(lambda t: relieved(compare(t)), "a long, b long")
        return found.distinct()

    def similar(self) -> DataFrame:
        """doc_id, n_shingles, component_id (an id), component (a number, also where ids are equal or null)."""
        first = stored(self.first_step())
        documents = first.filter(F.col("kind") == DOCUMENT)
        # equal sets of all batches count as one, the least node
        sets = documents.filter("digest is not null").groupBy("digest").agg(F.min("node").alias("of"))
        known = documents.filter("digest is not null").join(sets, "digest")
        nodes = stored(known.filter("node = of").select("node", "size", "spare_home", "spare_above", "home", "above"))
        members = stored(self.members(first.filter(F.col("kind") == PIECE), nodes))
        ties = stored(self.possible(self.ties(members), nodes))
        links = stored(self.verified(ties))
        labels = components(links)
        rest = self.hidden(members, nodes, labels)
        tied = ties.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
        rest = stored(rest.join(tied, ["a", "b"], "left_anti"))
        if rest.limit(1).count():
            more = stored(self.verified(rest))
            if more.limit(1).count():
                labels = components(links.unionByName(more))
        rows = documents.select("doc_id", "first", F.col("size").alias("n_shingles"))
        rows = rows.join(known.select(F.col("node").alias("first"), "of"), "first", "left").withColumn("node", F.coalesce("of", "first"))
        rows = rows.join(labels, "node", "left").withColumn("component", F.coalesce("component", "node"))
        least = rows.groupBy("component").agg(F.min("doc_id").alias("component_id"))
        null = lambda name: F.when(F.col(name) != NULL_ID, F.col(name)).alias(name)
        return rows.join(least, "component").select(null("doc_id"), "n_shingles", null("component_id"), "component")


def similar(docs: DataFrame, gram: int = GRAM, percent: int = PERCENT) -> DataFrame:
    return Join(docs, gram, percent).similar()


def one_of_each(docs: DataFrame, gram: int, percent: int) -> DataFrame:
    """The documents of docs, all columns, without those that are not the first of their component, by id.

    Documents without words have no partner and stay. Of rows with one id, as many as are the first of a component by
    that id stay, in the order of their texts.
    """
    found = similar(docs, gram, percent).filter(F.col("doc_id").eqNullSafe(F.col("component_id")))
    alone = found.groupBy("doc_id").agg(F.count_distinct("component").alias("__stay"))
    place = F.row_number().over(W.partitionBy("doc_id").orderBy(F.col("text").asc_nulls_first()))
    ranked = docs.withColumn("__place", place)
    own = F.coalesce(ranked["doc_id"], F.lit(NULL_ID))
    kept = ranked.join(alone.select(F.coalesce("doc_id", F.lit(NULL_ID)).alias("__id"), "__stay"), own == F.col("__id"))
    return kept.filter(F.col("__place") <= F.col("__stay")).select(*docs.columns)


def op10_parity_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar(documents(spark, sf_dir)).select("doc_id", "n_shingles", "component_id")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {"op10_parity_join": op10_parity_join}
SQL: dict[str, str] = {
    "op10_parity_join": rf"""
WITH RECURSIVE split AS (
    SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS words FROM documents),
shingle AS (
    SELECT DISTINCT doc_id, array_to_string(words[start : start + {GRAM - 1}], ' ') AS s
    FROM (SELECT doc_id, words, unnest(generate_series(1, greatest(1, len(words) - {GRAM - 1}))) AS start FROM split WHERE len(words) > 0)),
sizes AS (
    SELECT doc_id, count(*) AS n FROM shingle GROUP BY doc_id),
link AS (
    SELECT x.doc_id AS a, y.doc_id AS b FROM shingle x JOIN shingle y ON x.s = y.s AND x.doc_id <> y.doc_id
    JOIN sizes m ON m.doc_id = x.doc_id JOIN sizes n ON n.doc_id = y.doc_id
    GROUP BY ALL HAVING 100 * count(*) >= {PERCENT} * (any_value(m.n) + any_value(n.n) - count(*))),
reach AS (
    SELECT doc_id, doc_id AS other FROM documents
    UNION
    SELECT r.doc_id, l.b FROM reach r JOIN link l ON l.a = r.other)
SELECT r.doc_id, coalesce(any_value(n.n), 0)::BIGINT AS n_shingles, min(r.other) AS component_id
FROM reach r LEFT JOIN sizes n ON n.doc_id = r.doc_id GROUP BY r.doc_id""",
}
