"""Brute force on small fixtures with the odd cases: nulls, empty and long texts, repeated rows, clashing columns, empty tables."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from synthguard.llm import blocks, components, fingerprint, jaccard_join, language, language_model, line_dedup, metric_search, packing, quality, sentence_pieces, suffix_dedup
from synthguard.llm.textkernel import SPACE, Words

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau the of and ün Été".split()
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
FOLD = str.maketrans(UPPER, UPPER.lower())
SCHEMA = "doc_id long, text string, lang string, line string, h1 long, n long"


def _texts():
    rng = random.Random(5)
    prose = lambda n: " ".join(rng.choice(WORDS) for _ in range(n))
    passage, line = prose(90), "  This very common line is shared by MANY documents\t"
    out = []
    for i in range(60):
        t = prose(rng.randint(1, 120))
        if i % 5 == 0:
            t = t + "\n" + line.swapcase() if i % 10 else line + "\n" + t + "\n" + line
        if i % 7 == 0:
            t = t + "\n" + passage + "\n" + prose(5)
        out.append(t)
    base = prose(80).split()
    for i in range(12):  # near copies
        w = list(base)
        w[5 * i + 3] = f"edit{i}"
        out.append(" ".join(w))
    out += [out[3], out[3], "", " \n\t ", "one", "one two", "\n\n", "x" * 5000, prose(4000), None]
    return out


TEXTS = _texts()
ROWS = [(i, t, "en" if i % 3 else "fr", "clash", 1, 2) for i, t in enumerate(TEXTS)] + [(None, TEXTS[0], None, None, None, None)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(ROWS, SCHEMA).repartition(5)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def _of(df, *cols):
    return {r["doc_id"]: tuple(r[c] for c in cols) for r in df.collect()}


def test_words_and_packing_helpers():
    w = Words([b"Ab c\td", b"", b" x "])
    assert w.count.tolist() == [3, 0, 1] and w.doc.tolist() == [0, 0, 0, 2]
    assert w.hashes()[1] == Words([b"C"]).hashes()[0] and SPACE[32]
    x = np.unique(np.random.default_rng(1).integers(0, 2**63, 500).astype(np.uint64))
    assert (blocks.unpacked(blocks.packed(x)) == x).all()
    c = np.array([0, 1, 300, 70000])
    assert (blocks.unpacked_counts(blocks.packed_counts(c)) == c).all()
    assert [b for b, lo, hi in blocks.by_bucket(x, 4)] == [0, 1]


@pytest.mark.parametrize("parts", [1, 7])
def test_line_dedup(spark, docs, empty, parts):
    holders = collections.defaultdict(set)
    key = lambda s: s.strip(" \t\n\x0b\x0c\r").translate(FOLD)
    for i, t, *_ in ROWS:
        for s in (t or "").split("\n"):
            if i is not None and len(key(s)) >= 20:
                holders[key(s)].add(i)
    spark.conf.set("spark.sql.shuffle.partitions", parts)
    got = line_dedup.dedup_lines(spark, docs)
    assert set(docs.columns) <= set(got.columns)
    for r in got.collect():
        t = TEXTS[r["doc_id"]] if r["doc_id"] is not None else TEXTS[0]
        gone = lambda s: r["doc_id"] is not None and len(holders[key(s)]) >= 3 and r["doc_id"] < max(holders[key(s)])  # noqa: B023, E731
        keep = [s for s in (t or "").split("\n") if not gone(s)]
        assert (r["text"] or "") == "\n".join(keep) and r["_n_lines"] == len((t or "").split("\n"))
    assert line_dedup.dedup_lines(spark, empty).count() == 0
    spark.conf.set("spark.sql.shuffle.partitions", 4)


def test_line_dedup_of_one_hot_line(spark):
    df = spark.createDataFrame([(i, "the same long line again and again\nthe same long line again and again") for i in range(300)], "doc_id long, text string").repartition(9)
    got = _of(line_dedup.dedup_lines(spark, df), "_n_dropped")
    assert got[299] == (0,) and all(got[i] == (2,) for i in range(299))


def test_sentence_pieces(spark, docs, empty):
    import sentencepiece

    path = public_tokenizers.path("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    coder = sentence_pieces.PieceCoder(path)
    odd = ["  a  b\n\n c\td ▁x ﬁ ½", "x\x00y\x01z 梦想 👍🏽", "z" * 300 + " " * 40 + "y", "\r\n);\r"]
    for t in odd + [t or "" for t in TEXTS]:
        ids, n = coder.encode([t.encode()])
        assert ids.tolist() == sp.encode(t) and n.tolist() == [len(ids)]
        assert coder.decode(ids) == t.replace("▁", " ")
    out = sentence_pieces.encode(docs, path)
    assert all(r["ids"] == sp.encode((TEXTS[r["doc_id"]] if r["doc_id"] is not None else TEXTS[0]) or "") and r["decodes"] for r in out.collect())
    back = _of(sentence_pieces.decode(out, path), "text")
    assert all(back[i] == (t or "",) for i, t in enumerate(TEXTS))
    assert sentence_pieces.encode(empty, path).count() == 0


def test_quality(spark, empty):
    rng = random.Random(2)
    good = [" ".join(rng.choice(WORDS) for _ in range(60)) + "." for _ in range(80)]
    bad = [" ".join(rng.choice(WORDS).upper() + "!!" for _ in range(60)) for _ in range(40)]
    rows = [(i, t) for i, t in enumerate(good + bad)] + [(900, None), (901, ""), (None, good[0])]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("_label", F.lit(1))
    labels = spark.createDataFrame([(i, int(i < 80)) for i in range(0, 120, 2)] + [(1, None), (None, 0)], "doc_id long, quality int")
    got = _of(quality.score(df, quality.train(df, labels)), "score")
    assert all(got[i][0] > 0.5 for i in range(80)) and all(got[i][0] < 0.3 for i in range(80, 120))
    assert got[900] == got[901] and 0 <= got[900][0] <= 1 and got[None] == got[0]
    one = quality.train(df, labels.where("quality = 1"))
    assert all(r["score"] > 0.5 for r in quality.score(df, one).collect())
    assert quality.score(empty, quality.train(empty, labels)).count() == 0


def test_language(spark, empty):
    rng = random.Random(3)
    own = {"aa": "klo mni pra tes wub zor".split(), "bb": "ein und der von mit auf".split()}
    rows = [(i, " ".join(rng.choice(own[k]) for _ in range(40)), k) for i, k in enumerate(["aa", "bb"] * 60)] + [(500, None, "aa"), (501, "12 .. 3", "bb"), (502, "und der von", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = _of(language.identify(df, language.train(df.where("doc_id % 3 <> 0"))), "lang_pred", "score")
    assert all(got[i][0] == k for i, _, k in rows[:120])
    assert got[500] == got[501] == ("und", 0.0) and got[502][0] == "bb"
    assert all(r["lang_pred"] == "und" for r in language.identify(df, language.train(empty)).collect())


def _jaccard_classes(rows, n, percent):
    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(FOLD))
        sets[i] = {tuple(w[k : k + n]) for k in range(max(1, len(w) - n + 1))} if w else set()
    top = {i: i for i in sets}

    def root(x):
        while top[x] != x:
            x = top[x]
        return x

    ids = sorted(sets)
    for x in ids:
        for y in ids:
            if x < y and sets[x] and sets[y] and 100 * len(sets[x] & sets[y]) >= percent * len(sets[x] | sets[y]):
                a, b = sorted((root(x), root(y)))
                top[b] = a
    return {i: (len(sets[i]), root(i)) for i in ids}


@pytest.mark.parametrize(("words", "percent"), [(4, 85), (5, 80), (2, 50)])
def test_jaccard_join(spark, docs, empty, words, percent):
    got = _of(jaccard_join.similar_classes(spark, docs, words=words, percent=percent), "n_shingles", "component_id")
    want = _jaccard_classes([(i, t) for i, t, *_ in ROWS if i is not None], words, percent)
    assert {k: v for k, v in got.items() if k is not None} == want and got[None][1] is None
    if words == 4:
        assert jaccard_join.similar_classes(spark, empty).count() == 0


def test_components(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 101), (103, 101), (7, 7)]
    got = {r["node"]: r["comp"] for r in components.components(spark, spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(41)) and got[100] == got[101] == got[103] == 100


def _repeats(rows, length):
    starts = collections.defaultdict(list)
    for k, (_, t) in enumerate(rows):
        b = (t or "").encode()
        for s in range(len(b) - length + 1):
            starts[b[s : s + length]].append((k, s))
    gone = [np.zeros(len((t or "").encode()), bool) for _, t in rows]
    for where in starts.values():
        if len(where) > 1:
            for k, s in where:
                gone[k][s : s + length] = True
    return gone


@pytest.mark.parametrize(("length", "kinds"), [(200, 512), (200, 1), (100, 4)])
def test_suffix_dedup(spark, docs, empty, length, kinds):
    rows = [(i, t) for i, t, *_ in ROWS]
    gone = _repeats(rows, length)
    got = {r["doc_id"]: r for r in suffix_dedup.remove_repeats(spark, docs, length=length, kinds_in_lot=kinds, lot_bytes=3000).collect()}
    for (i, t), g in zip(rows, gone, strict=True):
        raw, r = np.frombuffer((t or "").encode(), np.uint8), got[i]
        runs = int((np.diff(np.concatenate(([0], g.astype(int)))) == 1).sum())
        assert (r["_n_bytes"], r["_n_removed"], r["_n_spans"]) == (len(raw), int(g.sum()), runs)
        assert r["_kept_sha256"] == hashlib.sha256(raw[~g].tobytes()).hexdigest()
    assert any(g.any() and not g.all() for g in gone)
    if kinds == 512:
        assert suffix_dedup.remove_repeats(spark, empty).count() == 0


def test_merged_transforms_equal_sorting():
    rng = np.random.default_rng(4)
    texts = [bytes(rng.integers(97, 99, 400, dtype=np.uint8)) + b"\xff" for _ in range(3)]
    for depth in (5, 8, 11):
        classes = suffix_dedup.merged_classes([suffix_dedup.Shard(np.frombuffer(t, np.uint8), depth) for t in texts], depth)
        seen = {}
        for t, c in zip(texts, classes, strict=True):
            round_ = t + t
            for p in range(len(t)):
                assert seen.setdefault(c[p], round_[p : p + depth]) == round_[p : p + depth]
        assert len(set(seen.values())) == len(seen)


def test_common_prefixes_of_merged_rows():
    rng = np.random.default_rng(6)
    texts = [bytes(rng.integers(97, 100, 300, dtype=np.uint8)) + b"\xff" for _ in range(3)]
    shards = [suffix_dedup.Shard(np.frombuffer(t, np.uint8), 16) for t in texts]
    for depth, step in ((16, 1), (16, 4), (10, 8)):
        source, common = suffix_dedup.merged_rows(shards, depth, step)
        rows = sorted((t + t)[p : p + depth] for t in texts for p in range(len(t)))
        assert sorted(np.bincount(source).tolist()) == [len(t) for t in texts]
        first = depth % step or step
        for k, (a, b) in enumerate(zip(rows[:-1], rows[1:], strict=True), 1):
            same = next((i for i in range(depth) if a[i] != b[i]), depth)
            told = depth if same == depth else 0 if same < first else first + (same - first) // step * step
            assert common[k] == told


def _doubled(n):
    """A word of n letters and its opposite, which sums of powers modulo 2**64 cannot tell apart from 1024 letters on."""
    x = "a"
    while len(x) < n:
        x += x.translate(str.maketrans("ab", "ba"))
    return x, x.translate(str.maketrans("ab", "ba"))


def _regular_rows():
    (a, b), (c, d) = _doubled(1024), _doubled(4096)
    texts = [a, b, c, d, f"{a} x {b}", f"{b} x {a}", f"some words {c[:700]}", f"other words {d[:700]}", f"{a[:256]}.", f"{b[:256]},", a + "!" + b]
    return list(enumerate(texts))


def test_regular_words_are_told_apart(spark):
    import sentencepiece
    from tokenizers import Tokenizer

    rows = _regular_rows()
    df = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    # packing
    path = public_tokenizers.path("word_bpe_49k.json")
    t, full = Tokenizer.from_file(path), {}
    full = {i: np.array([*t.encode(x, add_special_tokens=False).ids, 2], "<u4") for i, x in rows}
    for r in packing.pack(df, path).collect():
        assert r["ids_crc32"] == zlib.crc32(full[r["doc_id"]][r["start"] : r["start"] + r["length"]].tobytes())
    # pieces
    path = public_tokenizers.path("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    assert all(r["ids"] == sp.encode(rows[r["doc_id"]][1]) for r in sentence_pieces.encode(df, path).collect())
    # shingles
    assert _of(jaccard_join.similar_classes(spark, df, words=4, percent=85), "n_shingles", "component_id") == _jaccard_classes(rows, 4, 85)
    # repeats
    gone = _repeats(rows, 200)
    got = _of(suffix_dedup.remove_repeats(spark, df), "_n_removed", "_kept_sha256")
    assert all(got[i] == (int(g.sum()), hashlib.sha256(np.frombuffer(x.encode(), np.uint8)[~g].tobytes()).hexdigest()) for (i, x), g in zip(rows, gone, strict=True))
    # counts of words
    count = collections.Counter(w for _, x in rows for w in x.split()) + collections.Counter({None: len(rows)})
    n, v = sum(count.values()), len(count)
    got = _of(language_model.score(spark, df, F.lit(True)), "base_score")
    assert all(got[i][0] == pytest.approx(sum(math.log10((count[w] + 1) / (n + v + 1)) for w in [*x.split(), None])) for i, x in rows)


def test_words_whose_hashes_are_alike_are_compared(monkeypatch):
    monkeypatch.setattr(Words, "hashes", lambda self: np.full(len(self.start), 7, np.uint64))
    path = public_tokenizers.path("word_bpe_49k.json")
    coder = packing.CachedTokenizer(path)
    for texts in (["one two one", "three", "", "four one"], ["two two five"]):
        want = [coder.tokenizer.encode(t, add_special_tokens=False).ids for t in texts]
        ids, sizes = coder.encode([t.encode() for t in texts])
        assert sizes.tolist() == list(map(len, want)) and ids.tolist() == sum(want, [])


def test_pieces_of_long_unbroken_text():
    import time

    import sentencepiece

    path = public_tokenizers.path("piece_bpe_32k.model")
    sp, coder, rng = sentencepiece.SentencePieceProcessor(model_file=path), sentence_pieces.PieceCoder(path), random.Random(1)
    letters = lambda n, of="abcdefghijklmnopqrstuvwxyz": "".join(rng.choice(of) for _ in range(n))
    for text in [*(letters(rng.randint(1, 80), of) for of in ("ab", "thein", "abcdefgh") for _ in range(60)), letters(40_000), "the" * 9_000, "a" * 30_001, _doubled(1 << 15)[0]]:
        assert coder.encode([text.encode()])[0].tolist() == sp.encode(text)
    began = time.time()
    text = letters(1_000_000)
    assert coder.encode([text.encode()])[0].tolist() == sp.encode(text) and time.time() - began < 30


CLASH = ["_n_lines", "_N_Dropped", "_sg_doc", "_sg_print", "_SG_id", "_n_bytes", "_n_removed", "_n_spans", "_kept_sha256", "_sg_score", "score", "Lang_Pred", "rejected", "_sg_told", "row", "Cut", "doc", "print", "spans", "told", "scored", "keep_bitmap", "_sg_label", "sid", "comp", "h1", "block", "kind"]


def test_columns_of_any_name_pass(spark):
    rows = [(i, t) for i, t, *_ in ROWS[:12]] + [(None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string").select("*", *[F.lit(f"own {c}").alias(c) for c in CLASH])
    labels = spark.createDataFrame([(i, i % 2) for i in range(12)], "doc_id long, quality int")
    model = language.train(df.withColumn("lang", F.lit("aa")))
    outputs = {"_n_lines", "_n_dropped"}, {"_n_bytes", "_n_removed", "_n_spans", "_kept_sha256"}, {"score"}, {"score", "lang_pred", "rejected"}
    made = line_dedup.dedup_lines(spark, df), suffix_dedup.remove_repeats(spark, df), quality.score(df, quality.train(df, labels)), language.identify(df, model)
    for out, own in zip(made, outputs, strict=True):
        assert {c.lower() for c in out.columns} == {c.lower() for c in df.columns} | own and len(out.columns) == len({c.lower() for c in out.columns})
        got = out.collect()
        assert len(got) == len(rows) and all(r[c] == f"own {c}" for r in got for c in CLASH if c.lower() not in own)
    plain = df.select("doc_id", "text")
    assert sorted(map(str, jaccard_join.similar_classes(spark, df).collect())) == sorted(map(str, jaccard_join.similar_classes(spark, plain).collect()))
    assert packing.pack(df, public_tokenizers.path("word_bpe_49k.json")).count() and fingerprint.edited_by_next(df).count() == len(rows)
    assert language_model.score(spark, df, F.lit(True)).count() == len(rows) and sentence_pieces.encode(df, public_tokenizers.path("piece_bpe_32k.model")).count() == len(rows)


def test_long_texts_are_read_in_stretches():
    text = ("und der von " * 300 + "ß é").encode()
    whole = language.buckets(text)
    assert sorted(np.concatenate(list(language.stretches(text, step=100))).tolist()) == sorted(whole.tolist())
    assert quality.features(text, step=64).tolist() == quality.features(text).tolist()


def test_fingerprints(spark, docs, empty):
    rows = sorted(((i, t or "") for i, t, *_ in ROWS if i is not None), reverse=True) + [(None, TEXTS[0])]
    got = _of(fingerprint.edited_by_next(docs), "n_chars", "edited_sha256", "fingerprint", "near_edited", "near_next")
    for k, (i, t) in enumerate(rows):
        half, nxt = len(t) // 2, rows[(k + 1) % len(rows)][1]
        assert got[i][:2] == (len(t), hashlib.sha256((t[: len(t) - half] + nxt[:half]).encode()).hexdigest())
        assert 0 <= got[i][3] <= 1 and 0 <= got[i][4] <= 1
    assert got[3][2] == got[TEXTS.index(TEXTS[3], 4)][2] == got[73][2] if TEXTS[73] == TEXTS[3] else True
    assert fingerprint.edited_by_next(empty).count() == 0
    pairs = {(r["a"], r["b"]) for r in fingerprint.matches(fingerprint.fingerprints(docs.where("doc_id IS NOT NULL")), 0.6).collect()}
    sets = {i: set(s.tolist()) for (i, _), s in zip(rows[:-1], fingerprint.Spots()([t.encode() for _, t in rows[:-1]]), strict=True)}
    reps = {}
    for i in sorted(sets):
        reps.setdefault(frozenset(sets[i]), i)
    ids = sorted(reps.values())
    want = {frozenset((a, b)) for a in ids for b in ids if a < b and len(sets[a] & sets[b]) >= 0.6 * len(sets[a] | sets[b])}
    assert {frozenset(p) for p in pairs} == want


def test_exact_search(spark):
    rng = np.random.default_rng(6)
    x = rng.normal(size=(700, 8)).astype(np.float32)
    x[600:] = x[3]  # many copies
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(900, None), (901, [1.0, None]), (902, [float("nan")] * 8), (None, [1.0] * 8), (903, [0.5, -0.25])]
    whole = metric_search.whole_numbers(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), "vec_id", "embedding", 1024)
    v = {i: np.floor(1024 * np.pad(np.array(e, np.float64), (0, 8 - len(e)))).astype(np.int64) for i, e in rows if i is not None and i not in (900, 901, 902)}
    for page, block in ((100, 4096), (5000, 3)):
        got = collections.defaultdict(list)
        for r in metric_search.top_k(whole, whole.where("id % 100 = 0"), 10, page, block).orderBy("query_id", "rank").collect():
            got[r["query_id"]].append((r["vec_id"], r["score"]))
        for q in [i for i in v if i % 100 == 0]:
            want = sorted(((int(v[q] @ v[c]), -c) for c in v if c != q), reverse=True)[:10]
            assert got[q] == [(-c, s) for s, c in want]
    # clusters, one of them of copies: cells whose bound lies below the kth score are not visited
    centre = rng.normal(size=(12, 8))
    x2 = centre[rng.integers(0, 12, 1500)] + 0.02 * rng.normal(size=(1500, 8))
    x2[500:1000] = x2[0]
    v2 = np.floor(1024 * x2).astype(np.int64)
    many = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(v2)], "id long, v array<long>")
    got = collections.defaultdict(list)
    for r in metric_search.top_k(many, many.where("id % 50 = 0"), 10, 64, 7, 20).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    for q in range(0, 1500, 50):
        want = sorted(((int(v2[q] @ v2[c]), -c) for c in range(1500) if c != q), reverse=True)[:10]
        assert got[q] == [(-c, s) for s, c in want]
    tree = metric_search.MTree(np.arange(700), np.floor(1024 * x).astype(np.int64))
    tree.search(tree.vectors[5], 10, 5)
    assert tree.products < 700
    assert metric_search.top_k(whole.limit(0), whole.limit(0)).count() == 0


def test_packing(spark, docs, empty):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    t, window = Tokenizer.from_file(path), 256
    full = {i: np.array([*t.encode(x or "", add_special_tokens=False).ids, 2], "<u4") for i, x, *_ in ROWS}
    rows, cover, fill = packing.pack(docs, path, window=window).collect(), collections.Counter(), collections.defaultdict(list)
    for r in rows:
        own = full[r["doc_id"]]
        assert r["doc_tokens"] == len(own) and r["ids_crc32"] == zlib.crc32(own[r["start"] : r["start"] + r["length"]].tobytes())
        cover[r["doc_id"]] += r["length"]
        fill[r["sequence_id"]].append((r["offset"], r["length"]))
    assert all(cover[i] == len(x) for i, x in full.items())
    for pieces in fill.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= window and (at == window or at & (at - 1) == 0)
    assert packing.pack(empty, path).count() == 0
    p = packing.Packer(10, 0)
    p.levels[[4, 7]] = [3, 1]
    cost = {h: (-2 * p.levels[h] + 1 if h else 0) + (2 * p.levels[h + 3] + 1 if h + 3 < 10 else 0) for h in (0, 4, 7)}
    assert cost[p.level_for(3)] == min(cost.values())


def test_packing_of_words_that_normalise_to_the_mark():
    path = public_tokenizers.path("word_bpe_49k.json")
    texts = ["abc \u1fef x\u1fefy def", "\u1fef", "a ` b\u1fef``\u1fef c", "\u1f70 \u1fbd plain", "", "\u0301 e\u0301 \u2000\u1fef"]
    coder = packing.CachedTokenizer(path)
    want = [coder.tokenizer.encode(t, add_special_tokens=False).ids for t in texts]
    ids, sizes = coder.encode([t.encode() for t in texts])
    assert sizes.tolist() == list(map(len, want)) and ids.tolist() == sum(want, [])
    # a run with other marks than those between its words
    coder = packing.CachedTokenizer(path)
    coder._has_mark = lambda word: False
    ids, sizes = coder.encode([t.encode() for t in texts])
    assert sizes.tolist() == list(map(len, want)) and ids.tolist() == sum(want, [])


def test_language_model(spark, docs, empty):
    fold = lambda i: i is None or zlib.crc32(str(i).encode()) % 7 == 2
    tokens = [(i, [*re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(FOLD)), None]) for i, t, *_ in ROWS]
    count = collections.Counter(w for i, ws in tokens if not fold(i) for w in ws)
    n, v = sum(count.values()), len(count)
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7 == 2, F.lit(True))
    got = {r["doc_id"]: r for r in language_model.score(spark, docs, ~held, block_bytes=4000).collect()}
    for i, ws in tokens:
        r = got[i]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"], r["learnt"]) == (len(ws), sum(count[w] > 0 for w in ws), n, not fold(i))
        assert r["base_score"] == pytest.approx(sum(math.log10((count[w] + 1) / (n + v + 1)) for w in ws)) and r["score"] < 0
    whole = lambda k: sum(r[k] for r in got.values() if not r["learnt"])
    assert whole("score") > whole("base_score")
    again = {r["doc_id"]: r["score"] for r in language_model.score(spark, docs.repartition(2), ~held, block_bytes=10**7).collect()}
    assert all(again[i] == pytest.approx(got[i]["score"]) for i in got)
    assert language_model.score(spark, empty, ~held).count() == 0
