"""Each operator against brute force, and on odd tables."""

import collections
import hashlib
import re

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from taskmap.llm import bpe, learning, merkle, mixing, neighbours, parity, quality, suffixes, tokencount, toxicity, windows
from taskmap.llm.components import components
from taskmap.llm.registry import QUERIES


def texts_of(df):
    """(id, text) in the order of the corpus: null ids first, equal ids by text."""
    rows = [(r["doc_id"], r["text"] or "") for r in df.select("doc_id", "text").collect()]
    return sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0, r[1].encode()))


def collected(df, *columns):
    return sorted((tuple(r[c] for c in columns) for r in df.collect()), key=repr)


def sha(data):
    return hashlib.sha256(data).hexdigest()


# 1: BPE


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(bpe.vocabulary_path())


def encoded(df, library):
    out = []
    for i, t in texts_of(df):
        ids = library.encode(t, add_special_tokens=False).ids
        back = library.decode(ids, skip_special_tokens=False)
        out.append((i, len(ids), sha(np.array(ids, "<u4").tobytes()), sha(back.encode())))
    return sorted(out, key=repr)


def test_bpe(odd, nothing, library):
    columns = ("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")
    assert collected(bpe.encode_documents(odd), *columns) == encoded(odd, library)
    assert not bpe.encode_documents(nothing).collect()


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=40) | st.lists(st.sampled_from(["<|endoftext|>", "Don't", "İ", "ΑΣ", "é", "\x85", " ", "12", "!?"]), max_size=9).map("".join))
def test_bpe_on_any_text(library, text):
    own = bpe.loaded(bpe.vocabulary_path())
    ids = library.encode(text, add_special_tokens=False).ids
    assert own.encode(text) == ids and own.decode(ids) == library.decode(ids, skip_special_tokens=False)


def test_bpe_cuts_plain_runs_without_the_library(library):
    own = bpe.WordBPE(bpe.vocabulary_path())
    text = "Don't 12 cats, they'LL\x1c!?" * 3
    ids = library.encode(text, add_special_tokens=False).ids
    own.normalizer = own.splitter = None
    assert own.encode(text) == ids


@pytest.mark.parametrize("text", ["J\u030c", "I\u0307", "H\u0331s", "\u0130", "A\x0bB\x1cC", "na\u00efve,\u00c9T\u00c9"])
def test_bpe_normalizes_runs_as_whole_texts(library, text):
    own = bpe.loaded(bpe.vocabulary_path())
    for t in (text, f"x {text}", f"{text} X"):
        assert own.encode(t) == library.encode(t, add_special_tokens=False).ids


# 2: mixing


def filled(sizes, budget):
    """Targets by pouring what is left again and again."""
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: mixing.WEIGHTS[i % 3] for i, s in enumerate(order)}
    target, left, open_ = dict.fromkeys(order, 0.0), budget * sum(sizes.values()), set(order)
    while left > 1e-9 and open_:
        total, share = sum(weight[s] for s in open_), left
        left = 0.0
        for s in sorted(open_, key=str):
            target[s] += share * weight[s] / total
            if target[s] >= 2 * sizes[s]:
                left += target[s] - 2 * sizes[s]
                target[s] = 2.0 * sizes[s]
                open_.discard(s)
    return target


def test_mixing(odd, nothing, spark, tiny):
    for df in (odd, spark.read.parquet(f"{tiny}/documents.parquet")):
        got = mixing.mix(df).collect()
        sizes = collections.Counter()
        for r in got:
            assert r["size"] == len(re.findall(r"[^\x20\x09-\x0D]+", r["text"] or ""))
        plain = mixing.mix(df.select("doc_id", "text", "source")).collect()
        for r in plain:
            sizes[r["source"]] += r["size"]
        target = filled(sizes, mixing.BUDGET)
        taken = collections.Counter()
        for r in plain:
            assert r["taken"] <= 2 * r["size"] and r["source_size"] == sizes[r["source"]]
            assert r["target"] == pytest.approx(target[r["source"]], abs=1e-6)
            taken[r["source"]] += r["taken"]
        assert all(abs(taken[s] - target[s]) <= 0.5 for s in sizes)
    assert not mixing.mix(nothing).collect() and not mixing.mixed_stream(nothing, 2).collect()


def test_mixing_takes_any_names(make):
    """Columns named like those inside or those added: kept by the stream, replaced by the mix."""
    clash = ["size", "target", "source_size", "taken", "taken_first", "finish_first", "row", "doc", "none", "place", "range", "before", "start", "goal", "weight", "sent", "whole", "cut", "at", "a.b"]
    df = make([(i, f"word{i} " * (i % 7), "st"[i % 2]) for i in range(40)]).select("doc_id", "text", "source", *[F.concat(F.lit(f"{c}-"), "doc_id").alias(c) for c in clash])
    stream = mixing.mixed_stream(df, 3)
    assert stream.columns == df.columns
    rows = stream.collect()
    assert rows and all(r[c] == f"{c}-{r['doc_id']}" for r in rows for c in clash)
    got = mixing.mix(df)
    assert sorted(got.columns) == sorted({*df.columns, *mixing.ADDED})
    assert sum(r["taken"] for r in got.collect()) == sum(len(r["text"].split()) for r in rows)


def test_mixed_stream_is_the_mix(spark, tiny):
    df = spark.read.parquet(f"{tiny}/documents.parquet")
    taken = mixing.mix(df).agg(F.sum("taken")).head()[0]
    stream = mixing.mixed_stream(df, 4)
    assert stream.columns == df.columns
    assert stream.agg(F.sum(mixing.word_count(F.col("text")))).head()[0] == taken


# 3 and 5: classifiers


def test_toxicity_is_learnt_from_contrast():
    filler = "the of and to in is that was for on are with as at be this have from or had".split()
    rng = np.random.default_rng(0)
    def text(y):
        w = rng.choice(filler, 60).tolist()
        for at in rng.integers(0, 60, 4 * y):
            w[at] = str(rng.choice(["grumble", "snarl", "sneer"]))
        return " ".join(w)

    sample = [(y, text(y)) for y in (0, 1) for _ in range(60)]
    model = toxicity.fit(sample)
    gain = model.gains()
    score = lambda t: float(model.score(np.array([model.features(t, gain)], float))[0])
    assert np.mean([score(text(1)) >= 0.7 for _ in range(40)]) > 0.9
    assert np.mean([score(text(0)) >= 0.7 for _ in range(40)]) == 0
    # deep inside a long text counts as much
    assert score(" ".join([text(0)] * 50 + [text(1)] + [text(0)] * 50)) >= 0.7


def test_classifiers_on_odd_tables(odd, nothing, spark):
    empty = toxicity.fit([])
    assert {r["predicted"] for r in toxicity.score_documents(odd, empty).collect()} <= {0, 1}
    assert toxicity.score_documents(odd, empty).count() == odd.count() and not toxicity.score_documents(nothing, empty).count()
    none = quality.fit([])
    assert all(0 <= r["score"] <= 1 for r in quality.score_documents(odd, none).collect())
    assert quality.keep_good(odd, none).columns == odd.columns


def test_toxicity_in_phrases():
    """Phrases of five words that are ordinary one by one."""
    import random

    rng = random.Random(3)
    usual = ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(2, 8))) for _ in range(800)]
    phrases = [[rng.choice(usual) for _ in range(5)] for _ in range(6)]

    def text(y):
        w = [rng.choice(usual) for _ in range(60)]
        if y:
            at = rng.randrange(50)
            w[at : at + 5] = rng.choice(phrases)
        return " ".join(w)

    sample = [(y, text(y)) for _ in range(200) for y in (0, 1)]
    model = toxicity.fit(sample)
    predicted = [[model.score(toxicity.measured(model, [(y, text(y))]))[0] >= toxicity.THRESHOLD for _ in range(100)] for y in (0, 1)]
    assert np.mean(predicted[0]) <= 0.01 and np.mean(predicted[1]) >= 0.9


def test_toxicity_scores_by_brute_force(spark, small):
    """Every window of every text compressed anew, without caches or shortcuts."""
    import zstandard

    docs, labels = (spark.read.parquet(f"{small}/{t}.parquet") for t in ("documents", "labels"))
    known = {r["doc_id"]: r["toxic"] for r in labels.collect()}
    rows = texts_of(docs)
    model = toxicity.fit([(known[i], t) for i, t in rows if i in known])

    def compressor(content):
        told = zstandard.ZstdCompressionParameters.from_level(toxicity.LEVEL, min_match=toxicity.MIN_MATCH, window_log=17, write_content_size=False, write_checksum=False, write_dict_id=False)
        return zstandard.ZstdCompressor(compression_params=told, dict_data=zstandard.ZstdCompressionDict(content + toxicity.BEFORE, dict_type=zstandard.DICT_TYPE_RAWCONTENT))

    plain, toxic = compressor(model.ordinary), compressor(model.toxic)
    got = {r["doc_id"]: r["score"] for r in toxicity.score_documents(docs, model).collect()}
    for i, t in rows[:60]:
        w = re.findall(r"[^\W\d_]+", t.lower())
        gains = [0, 0, 0, 0]
        for n in range(1, model.most + 1):
            for at in range(len(w) - n + 1):
                window = " ".join(w[at : at + n])
                if n > 1 and not set(w[at : at + n]) <= model.known:
                    continue
                block = toxicity.BEFORE + toxicity.OPEN + window.encode() + toxicity.CLOSE + toxicity.BEHIND
                a, b = len(plain.compress(block)), len(toxic.compress(block))
                gains.append(a - b if b <= model.longest[min(len(window.encode()), toxicity.LONGEST)] else 0)
        top = sorted(gains, reverse=True)[:4]
        z = np.dot(model.weights, [top[0], top[0] + top[1], sum(top), 1])
        assert got[i] == pytest.approx(1 / (1 + np.exp(-z)), abs=1e-9)


def test_quality_scores_by_brute_force(spark, tiny):
    """N-grams hashed one by one into a dictionary, weights looked up one by one."""
    import xxhash

    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    model = quality.trained(spark, docs, tiny)
    got = {r["doc_id"]: r["score"] for r in quality.score_documents(docs, model).collect()}
    mask = (1 << 64) - 1

    def form(word):
        return re.sub(r"\d+", "9", re.sub(r"[A-Z]+", "A", re.sub(r"[^\W\d_A-Z]+", "a", word)))

    for i, t in texts_of(docs):
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        slots = []
        for runs in ([xxhash.xxh3_64_intdigest(x.encode()) for x in w], [xxhash.xxh3_64_intdigest(form(x).encode(), 1) for x in w]):
            slots += [h >> (64 - quality.BITS) for h in runs]
            slots += [((a * 0x9DDFEA08EB382D69 + (b ^ (b >> 29)) * 0xD6E8FEB86659FD93) & mask) >> (64 - quality.BITS) for a, b in zip(runs, runs[1:])]
        z = model.intercept + (quality.SCALE * sum(float(model.weights[s]) for s in slots) / len(slots) if slots else 0)
        assert got[i] == pytest.approx(1 / (1 + np.exp(-min(30, max(-30, z)))), abs=1e-5)


@pytest.mark.parametrize("name, label, n, held, threshold, least_recall, least_precision", [("op5_quality", "quality", 5, 0, 0.3, 0.95, 0.93), ("op3_toxicity", "toxic", 3, 1, 0.7, 0.6, 0.8)])
def test_held_out(spark, small, name, label, n, held, threshold, least_recall, least_precision):
    """On rows not learnt from; predicting one label for all fails the one or the other bound."""
    import zlib

    got = {r["doc_id"]: r for r in QUERIES[name](spark, small).collect()}
    labels = {r["doc_id"]: r[label] for r in spark.read.parquet(f"{small}/labels.parquet").collect()}
    for i, r in got.items():
        assert r["held_out"] == (zlib.crc32(str(i).encode()) % n == held) and r["predicted"] == int(r["score"] >= threshold)
    out = [(got[i]["predicted"], y) for i, y in labels.items() if got[i]["held_out"]]
    both = sum(p and y for p, y in out)
    assert both >= least_recall * sum(y for _, y in out) and both >= least_precision * sum(p for p, _ in out)


def test_learning_from_odd_labels(spark, make):
    """Null, contradictory, foreign and missing labels, repeated rows; an empty table."""
    docs = make([(1, "good words here"), (2, None), (2, "twice"), (3, "bad words there"), (None, "no id"), (4, "")])
    labels = lambda rows: spark.createDataFrame(rows, "doc_id long, quality int, toxic int, text string")
    told = labels([(1, 1, 0, "x"), (1, 0, 0, "x"), (2, None, 1, "x"), (3, 0, 7, "x"), (None, 1, 1, "x"), (9, 1, 1, "x")])
    sample = learning.labelled_sample(docs, told, "quality", F.lit(True), (10, 10))
    assert sorted((r["y"], r["text"]) for r in sample.collect()) == [(0, "bad words there"), (1, "good words here")]
    assert sorted((r["y"], r["text"]) for r in learning.labelled_sample(docs, told, "toxic", F.lit(True), (10, 10)).collect()) == [(0, "good words here"), (1, ""), (1, "twice")]
    for df in (sample, learning.labelled_sample(docs, labels([]), "quality", F.lit(True), (10, 10))):
        model = learning.fitted(df, quality.fit)
        assert 0 <= model.score(np.zeros(0, np.int64)) <= 1
        assert 0 <= learning.fitted(df, toxicity.fit).score(np.zeros((1, 3)))[0] <= 1


# 4: Merkle trees


def test_merkle(odd, nothing):
    rows = texts_of(odd)
    got = collected(merkle.compared_with_next(odd, 3), "doc_id", "n_chars", "edited_sha256", "fingerprint")
    want = []
    for (i, a), (_, b) in zip(rows, rows[1:] + rows[:1]):
        want.append((i, len(a), sha(merkle.edited(a, b).encode()), merkle.tree(a).fingerprint))
    assert got == sorted(want, key=repr)
    assert not merkle.compared_with_next(nothing, 3).collect()
    assert merkle.fingerprints(odd).count() == odd.count()


@settings(max_examples=100, deadline=None)
@given(st.text("ab.\n ", max_size=120), st.text("ab.\n ", max_size=120))
def test_merkle_compares(a, b):
    x, y = merkle.tree(a), merkle.tree(b)
    assert (x.fingerprint == y.fingerprint) == (a == b)
    likeness, _, _ = merkle.compare(x, y)
    assert 0 <= likeness <= 1 and (likeness == 1) >= (a == b)
    assert "".join(merkle.phrases(a)) == a
    assert merkle.compare(y, x)[0] == pytest.approx(likeness)


def test_merkle_locates_an_edit():
    a = "".join(f"Sentence {i} stands here. Another follows it.\n" for i in range(50))
    b = a.replace("Sentence 25 stands", "Sentence 25 moved")
    likeness, ours, theirs = merkle.compare(merkle.tree(a), merkle.tree(b))
    assert likeness > 0.97 and ours == ["Sentence 25 stands here. "] and theirs == ["Sentence 25 moved here. "]


# 6: token counts


def test_token_counts(odd, nothing):
    scores = tokencount.piece_scores(tokencount.vocabulary_path())

    def best(token):
        table = [(0, 0)]
        for i in range(1, len(token) + 1):
            size = len(token[i - 1].encode())
            options = [(table[i - 1][0] + tokencount.BYTE * size, table[i - 1][1] - size)]
            options += [(table[j][0] + scores[token[j:i]], table[j][1] - 1) for j in range(max(0, i - 24), i) if token[j:i] in scores]
            table.append(max(options))
        return -table[-1][1]

    want = sorted(((i, len(t.encode().split()), sum(best(tokencount.START + w.decode()) for w in t.encode().split())) for i, t in texts_of(odd)), key=repr)
    assert collected(tokencount.token_counts(odd), "doc_id", "n_words", "n_tokens") == want
    assert not tokencount.token_counts(nothing).collect()


# 7: suffix arrays


def removed_bytes(rows, length=suffixes.LENGTH):
    seen, out = set(), []
    for i, t in rows:
        raw = t.encode()
        gone = np.zeros(len(raw), bool)
        for a in range(len(raw) - length + 1):
            window = raw[a : a + length]
            if window in seen:
                gone[a : a + length] = True
            seen.add(window)
        kept = bytes(x for x, g in zip(raw, gone) if not g)
        out.append((i, len(raw), int(gone.sum()), sha(kept)))
    return sorted(out, key=repr)


LINE = "a very common line of a certain length that stands in every document and then goes on differently, "


def passages(make):
    rng = np.random.default_rng(3)
    fresh = lambda n: " ".join("".join(rng.choice(list("abcdefgh"), 6)) for _ in range(n))
    shared = fresh(40)
    rows = [(i, fresh(30) + LINE + fresh(10) + (shared if i % 3 == 0 else "") + fresh(5)) for i in range(40)]
    return make(rows + [(50, "x" * 1000), (51, "xy" * 400), (52, rows[7][1]), (53, rows[7][1][50:300])])


@pytest.mark.parametrize("hot", [{}, {"hot_in_batch": 1, "hot": 2}])
def test_suffixes(odd, nothing, make, hot):
    for df in (odd, passages(make)):
        assert collected(suffixes.repeated_bytes(df, **hot), "doc_id", "n_bytes", "n_removed", "kept_sha256") == removed_bytes(texts_of(df))
    assert not suffixes.repeated_bytes(nothing).collect()


def test_suffix_family_levels():
    rng = np.random.default_rng(5)
    family, seen = suffixes.SuffixFamily(8), set()
    for _ in range(30):
        texts = [bytes(rng.integers(97, 99, rng.integers(0, 40)).astype(np.uint8)) for _ in range(3)]
        want = []
        for t in texts:
            for a in range(len(t) - 7):
                want.append(t[a : a + 8] in seen)
                seen.add(t[a : a + 8])
        assert family.add(texts).tolist() == want
        sizes = [len(x) for x in family.levels]
        assert all(a >= 2 * b for a, b in zip(sizes, sizes[1:])) and sum(sizes) == len(seen)


def test_without_repeats_keeps_columns(odd):
    got = suffixes.without_repeats(odd)
    assert got.columns == odd.columns and got.dtypes == odd.dtypes and got.count() == odd.count()
    assert {r["batch"] for r in got.collect()} == {7}


def test_removal_leaves_other_characters(spark):
    twice = "é" + "".join(f"{i * i}ж" for i in range(400))
    rows = [(0, "a \ufffd b", 5), (1, None, None), (2, "\ufffdone à" + twice, 0), (3, "two â" + twice + "\ufffd", 0)]
    got = {r["doc_id"]: (r["text"], r["n_chars"]) for r in suffixes.without_repeats(spark.createDataFrame(rows, "doc_id long, text string, n_chars long")).collect()}
    assert got[0] == rows[0][1:] and got[1] == (None, None)
    # of what both have, one copy goes; the marks before and behind stay, and nothing is cut within a character
    assert got[2] == (rows[2][1], 0) or got[2][0].startswith("\ufffdone ")
    assert got[3] == (rows[3][1], 0) or (got[3][0].endswith("\ufffd") and got[3][0].startswith("two "))
    assert any(n == len(t) and n < 100 for t, n in (got[2], got[3]))


def test_spans_of_whole_characters():
    raw = "aéж€b".encode()  # a, two bytes, two bytes, three bytes, b
    assert suffixes.whole_characters(raw, np.array([[2, 4], [6, 7]])).tolist() == [[1, 5], [5, 8]]
    assert suffixes.whole_characters(raw, np.array([[0, 1], [8, 9]])).tolist() == [[0, 1], [8, 9]]


# 8: neighbours


def test_neighbours(spark, tiny):
    v = spark.read.parquet(f"{tiny}/embeddings.parquet")
    odd = spark.createDataFrame([(1000, None, 0), (1100, [0.0] * 64, 0), (1200, [float("nan")] * 64, 0), (1300, [1.0] * 3, 0), (1400, [None] * 64, 0)], v.schema)
    got = collections.defaultdict(list)
    for r in neighbours.nearest(v.unionByName(odd), F.col("vec_id") % 100 == 0).collect():
        got[r["query_id"]].append((r["rank"], r["score"], r["vec_id"]))
    rows = v.collect()
    ids, x = np.array([r["vec_id"] for r in rows]), np.array([r["embedding"] for r in rows], float)
    hits = 0
    queries = [i for i in ids if i % 100 == 0]
    assert set(got) == set(queries)
    for i in queries:
        d = np.sqrt(((x - x[ids == i][0]) ** 2).sum(1))
        d[ids == i] = np.inf
        best = ids[np.lexsort((ids, d))[:10]]
        own = sorted(got[i])
        assert [r for r, _, _ in own] == list(range(1, 11)) and [s for _, s, _ in own] == sorted(s for _, s, _ in own)
        hits += len(set(best) & {j for _, _, j in own})
    assert hits / (10 * len(queries)) >= 0.9


def test_neighbours_in_cells(spark, tiny, monkeypatch):
    v = spark.read.parquet(f"{tiny}/embeddings.parquet").limit(300)
    whole = collected(neighbours.nearest(v, F.col("vec_id") % 100 == 0, confidence=0.99999), "query_id", "rank", "vec_id")
    monkeypatch.setattr(neighbours, "CELL", 60)
    assert collected(neighbours.nearest(v, F.col("vec_id") % 100 == 0, confidence=0.99999), "query_id", "rank", "vec_id") == whole
    assert not neighbours.nearest(v.limit(0), F.col("vec_id") % 100 == 0).collect()


def test_neighbours_of_common_vectors(spark, monkeypatch):
    """A vector that most rows have, ties everywhere, fewer candidates than asked for, further columns: as brute force says."""
    rng = np.random.default_rng(0)
    few = [rng.integers(-2, 3, 16).astype(float) + 0.5 for _ in range(6)]
    rows = [(int(i), few[0] if i % 3 else few[rng.integers(6)]) for i in rng.permutation(400)]
    schema = "vec_id long, embedding array<double>, rank int, vector string, cell int"
    frame = lambda some: spark.createDataFrame([(i, v.tolist(), 1, "x", 2) for i, v in some], schema)

    def brute(some):
        out = []
        for q, x in some:
            if q % 100 == 0:
                near = sorted((float(np.sqrt(((x - v) ** 2).sum())), i) for i, v in some if i != q)[:10]
                out += [(q, r + 1, i, round(s, 9)) for r, (s, i) in enumerate(near)]
        return sorted(out)

    for some, cell in ((rows, 20_000), (rows, 50), ([r for r in rows if r[0] % 50 == 0], 20_000)):
        monkeypatch.setattr(neighbours, "CELL", cell)
        got = neighbours.nearest(frame(some), F.col("vec_id") % 100 == 0, confidence=0.9999999)
        assert sorted((r["query_id"], r["rank"], r["vec_id"], round(r["score"], 9)) for r in got.collect()) == brute(some)


def test_chi_square():
    assert neighbours.chi_square_cdf(neighbours.chi_square_quantile(0.95, 8), 8) == pytest.approx(0.95)
    assert neighbours.chi_square_quantile(0.95, 8) == pytest.approx(15.507, abs=1e-3)


# 9: windows


def removed_words(rows, length=windows.LENGTH):
    first, out = {}, []
    for i, t in rows:
        w = t.encode().split()
        gone = [False] * len(w)
        for a in range(len(w) - length + 1):
            key = tuple(w[a : a + length])
            if key in first and first[key] != i:
                gone[a : a + length] = [True] * length
            first.setdefault(key, i)
        kept = b" ".join(x for x, g in zip(w, gone) if not g)
        out.append((i, len(w), sum(gone), sha(kept)))
    return sorted(out, key=repr)


def test_windows(odd, nothing, make):
    for df in (odd, passages(make)):
        assert collected(windows.repeated_words(df), "doc_id", "n_words", "n_removed", "kept_sha256") == removed_words(texts_of(df))
    assert not windows.repeated_words(nothing).collect()


# 10: parity join


def classes(rows, gram, percent):
    sets = []
    for _, t in rows:
        w = t.encode().translate(parity.LOWER).split()
        sets.append({tuple(w[a : a + gram]) for a in range(len(w) - gram + 1)} if len(w) >= gram else ({tuple(w)} if w else set()))
    parent = list(range(len(rows)))

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return sorted(((i, len(sets[n]), rows[find(n)][0]) for n, (i, _) in enumerate(rows)), key=repr)


def near_copies(make):
    rng = np.random.default_rng(9)
    base = [f"w{i}" for i in rng.integers(0, 5000, 150)]
    rows = []
    for i in range(60):
        w = list(base)
        for at in rng.integers(0, len(w), rng.integers(0, 9)):
            w[at] = f"e{rng.integers(0, 10**6)}"
        rows.append((i, " ".join(w)))
    return make(rows + [(100 + i, f"short text {i % 3}") for i in range(9)] + [(200, "Case CASE case"), (201, "case case CASE")])


@pytest.mark.parametrize("gram, percent", [(3, 90), (5, 80)])
def test_parity_join(odd, nothing, make, gram, percent):
    for df in (odd, near_copies(make)):
        assert collected(parity.similar(df, gram, percent), "doc_id", "n_shingles", "component_id") == classes(texts_of(df), gram, percent)
    assert not parity.similar(nothing, gram, percent).collect()


def test_parity_bound():
    rng = np.random.default_rng(2)
    bands = parity.Bands(80)
    for _ in range(50):
        own = np.unique(rng.integers(0, 1 << 63, 200).astype(np.uint64))
        other = np.unique(np.concatenate((own[: 200 - rng.integers(0, 60)], rng.integers(0, 1 << 63, rng.integers(0, 60)).astype(np.uint64))))
        apart = len(np.setxor1d(own, other))
        assert np.bitwise_count(bands.short(own, 20) ^ bands.short(other, 20)).sum() <= apart
        assert (bands.sketch(own, 20) != bands.sketch(other, 20)).sum() <= apart


@pytest.mark.parametrize("gram, percent, edits", [(3, 90, 8), (5, 80, 7)])
def test_parity_join_in_a_crowd(make, gram, percent, edits):
    """Copies about the threshold away from a common text and from each other, passages that many share, links by way of others."""
    rng = np.random.default_rng(4)
    word = lambda: f"w{rng.integers(0, 10**7)}"
    base, passage = [word() for _ in range(160)], [word() for _ in range(40)]
    rows = []
    for _ in range(120):
        w = list(base)
        for at in rng.integers(0, len(w), rng.integers(0, edits + 1)):
            w[at] = word()
        rows.append(w)
    for _ in range(60):
        rows.append([word() for _ in range(rng.integers(20, 60))] + passage + [word() for _ in range(rng.integers(0, 60))])
    chain = [word() for _ in range(150)]
    for i in range(12):
        chain = chain[: 12 * i] + [word() for _ in range(2)] + chain[12 * i + 2 :]
        rows.append(chain)
    order = rng.permutation(len(rows))
    df = make([(int(i), " ".join(rows[n])) for n, i in enumerate(order)] + [(1000 + i, " ".join(rows[i])) for i in range(5)])
    got = collected(parity.similar(df, gram, percent), "doc_id", "n_shingles", "component_id")
    assert got == classes(sorted(texts_of(df)), gram, percent)


def test_one_of_each(odd):
    kept = parity.one_of_each(odd, 5, 80)
    assert kept.columns == odd.columns
    ids = [r["doc_id"] for r in kept.collect()]
    assert 4 in ids and ids.count(5) == 0 and ids.count(9) == 2 and {1, 2, 3} <= set(ids)


def test_components(spark):
    links = [(i, i + 1) for i in range(0, 40)] + [(100, 105), (105, 103)] + [(200, i) for i in range(201, 230)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[103] == got[105] == 100 and got[229] == 200
