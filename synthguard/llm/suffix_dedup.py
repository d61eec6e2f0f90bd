"""Removal of every byte that lies in a string of `length` bytes found at two starts or more, over the whole corpus.

1. Anchors. Each window of `length` bytes has an anchor, its least hashed n-gram (the leftmost of equals); equal windows
   have equal anchors at equal places. Neighbouring windows with one anchor form an occurrence: all bytes its windows
   cover, its extent. Occurrences whose anchor stands once in the corpus hold no repeat.
2. Equal extents are one from here on: the whole of them is repeated, and one of them is looked at for the others.
3. Of anchors with several extents, each extent is cut out of its text, and its windows fall into zones by the anchor's place in
   them. A zone has a core, which all its windows hold: if no other zone has it, none of them is repeated. Zones that
   equal another are one again. What is left are zones through which a border of a repeat runs.
4. Those of one core meet in one task, in lots of bounded size. A lot is dealt into shards; each shard gets a suffix order
   and its Burrows-Wheeler transform, and the shards' transforms are merged by refining their interleave: each round stably sorts the merged
   transform by the symbols in front (eight bytes a round), which orders all rows by eight bytes more without a look at the
   suffixes. The round that first parts two neighbouring rows gives their common prefix; runs of rows with common prefixes of `length` bytes are
   the repeated intervals.
5. A core with more surroundings than a lot holds is cut into narrower zones (16 windows, then 4, then 1), whose longer cores
   part those surroundings; the core of a single window is that window, and has one surrounding.

Anchors only bring together what may be equal, so an anchor that two grams share costs time and nothing else. Extents, cores and zones
are equal where their 64-bit XXH3 hashes are, within one anchor's.

Defined cases: null text counts as empty; rows that share text are repeats of each other, so texts of `length` bytes or more that occur
twice lose all bytes, repeated rows included; a null id is an id like others; strings are judged on the input; text that is
returned drops bytes of characters that were cut apart; extra columns pass through.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.llm.common import carried, handed_back, staged, table, text_or_empty
from synthguard.llm.textkernel import BYTE_VALUE, U64, chunks, mix

GRAM = 48
#: Bytes of text that a task works on at a time; some dozen arrays of eight times that stand in its memory.
STRETCH = 1 << 19
_OCCURRENCE = "anchor long, extent long, doc long, print long, place long"
_LOW = U64(0xFFFFFFFF)


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(x.view(np.int64))


def _grams(buf: np.ndarray, gram: int) -> np.ndarray:
    """A number for each n-gram, by which anchors are picked; different n-grams may share one."""
    step = 0xD1342543DE82EF95  # odd
    up, down = np.full(len(buf), step, U64), np.full(len(buf), pow(step, -1, 1 << 64), U64)
    up[0] = down[0] = 1
    np.cumprod(up, out=up)
    np.cumprod(down, out=down)
    h = np.zeros(len(buf) + 1, U64)
    np.cumsum(BYTE_VALUE[buf] * up, out=h[1:])
    return mix((h[gram:] - h[:-gram]) * down[: len(buf) - gram + 1])


def _hashed(buf: bytes, start: np.ndarray, stop: np.ndarray, seeds: np.ndarray | None = None) -> np.ndarray:
    """64-bit hashes of buf[start:stop], each with its own seed where seeds are given."""
    view, of = memoryview(buf), xxhash.xxh3_64_intdigest
    if seeds is None:
        found = (of(view[a:b]) for a, b in zip(start.tolist(), stop.tolist(), strict=True))
    else:
        found = (of(view[a:b], k) for a, b, k in zip(start.tolist(), stop.tolist(), seeds.tolist(), strict=True))
    return np.fromiter(found, U64, len(start))


def occurrences(texts: list[bytes], length: int, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """text, anchor place, first and last window start (in the text), anchor, hash of all that the windows cover."""
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    begin = np.cumsum(sizes) - sizes
    joined = b"".join(texts)
    buf = np.frombuffer(joined, np.uint8)
    none = tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.int64, U64, U64))
    wide = length - gram + 1
    n = len(buf) - gram + 1
    if not (sizes >= length).any():
        return none
    grams = _grams(buf, gram)
    order = (grams & ~_LOW) | np.arange(n, dtype=U64)
    padded = np.full(-(-n // wide) * wide, ~U64(0))
    padded[:n] = order
    rows = padded.reshape(-1, wide)
    ahead = np.minimum.accumulate(rows, 1).ravel()
    behind = np.ascontiguousarray(np.minimum.accumulate(rows[:, ::-1], 1)[:, ::-1]).ravel()
    starts = n - wide + 1
    anchor = (np.minimum(behind[:starts], ahead[wide - 1 : wide - 1 + starts]) & _LOW).astype(np.int64)
    del ahead, behind, padded, rows, order
    inside = np.zeros(starts + 1, np.int8)  # windows that lie in one text
    for b, s in zip(begin[sizes >= length].tolist(), sizes[sizes >= length].tolist(), strict=True):
        inside[b] += 1
        inside[b + s - length + 1] -= 1
    inside = np.cumsum(inside[:-1]) > 0
    new = np.ones(starts, bool)
    new[1:] = (anchor[1:] != anchor[:-1]) | (inside[1:] != inside[:-1])
    at = np.flatnonzero(new)
    until = np.append(at[1:], starts) - 1
    at, until = at[inside[at]], until[inside[at]]
    p = anchor[at]
    text = np.searchsorted(begin, at, "right") - 1
    # of empty texts at the same place the last is found, which is the one that holds the bytes
    base = begin[text]
    return text, p - base, at - base, until - base, grams[p], _hashed(joined, at, until + length)


def _find(length: int):
    def run(batches):
        for b in batches:
            doc, mark, texts = b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False), [x or b"" for x in b.column(2).to_pylist()]
            for at, some in chunks(texts, STRETCH):
                t, p, first, last, anchor, extent = occurrences(some, length)
                place = p << 16 | (p - first) << 8 | (p - last)
                yield pa.RecordBatch.from_arrays([_signed(anchor), _signed(extent), pa.array(doc[at + t]), pa.array(mark[at + t]), pa.array(place)], names=["anchor", "extent", "doc", "print", "place"])

    return run


def suffix_order(text: np.ndarray, depth: int) -> np.ndarray:
    """Rotations of text in the order of their first depth symbols (at least), by doubling."""
    n = len(text)
    rank = text.astype(np.int64)
    step = 1
    while True:
        key = rank * (n + 257) + np.roll(rank, -step)
        order = np.argsort(key, kind="stable")
        s = key[order]
        rank = np.empty(n, np.int64)
        rank[order] = np.cumsum(np.concatenate(([0], s[1:] != s[:-1])))
        step *= 2
        if step >= depth or rank[order[-1]] == n - 1:
            return order


class Shard:
    """A text's suffix order and its transform: for each row the symbols in front, `step` of them as one number."""

    def __init__(self, text: np.ndarray, depth: int):
        self.text, self.order = text.astype(U64), suffix_order(text, depth)

    def transform(self, step: int) -> np.ndarray:
        front = np.zeros(len(self.text), U64)
        for k in range(step, 0, -1):
            front = front << U64(8) | np.roll(self.text, k)
        return front[self.order]


def merged_rows(shards: list[Shard], depth: int, step: int = 8) -> tuple[np.ndarray, np.ndarray]:
    """The shards' transforms merged: for each row the shard it comes from, and how many symbols (rounded down to what the
    rounds have told, depth at most) it has in common with the row before."""
    sizes = np.array([len(s.order) for s in shards])
    ends = np.cumsum(sizes)
    source = np.repeat(np.arange(len(shards), dtype=np.uint8 if len(shards) < 256 else np.int32), sizes)
    block = np.zeros(len(source), np.int32)
    common = np.full(len(source), depth, np.int32)
    common[:1] = 0
    rounds = [depth % step] * (depth % step > 0) + [step] * (depth // step)
    ordered = 0
    for k, wide in enumerate(rounds):
        if k == 0 or wide != rounds[k - 1]:  # symbols as ranks, which keep their order
            distinct, rank = np.unique(np.concatenate([s.transform(wide) for s in shards]), return_inverse=True)
            rank, few = rank.astype(np.int32), len(distinct) <= 1 << 16
        # the merged transform: the shards' rows in the order of the interleave
        symbols = np.empty(len(source), np.int32)
        for j in range(len(shards)):
            symbols[source == j] = rank[ends[j] - sizes[j] : ends[j]]
        if few:
            move = np.argsort(symbols.astype(np.uint16), kind="stable")
        else:
            move = np.argsort((symbols & 0xFFFF).astype(np.uint16), kind="stable")
            move = move[np.argsort((symbols[move] >> 16).astype(np.uint16), kind="stable")]
        source, block, now = source[move], block[move], symbols[move]
        edge = np.zeros(len(block), bool)
        edge[1:] = (now[1:] != now[:-1]) | (block[1:] != block[:-1])
        # a border between rows stays where it is once a round has drawn it
        common[edge & (common == depth)] = ordered
        ordered += wide
        block = np.cumsum(edge, dtype=np.int32)
        if block[-1] == len(block) - 1:
            break  # no two rows are alike
    return source, common


def merged_classes(shards: list[Shard], depth: int, step: int = 8) -> list[np.ndarray]:
    """For each shard, by place in its text, the number of the interval of rows whose next depth symbols are equal in all shards."""
    source, common = merged_rows(shards, depth, step)
    interval = np.cumsum(common < depth, dtype=np.int32)
    out = []
    for j, s in enumerate(shards):
        by_place = np.empty(len(s.order), np.int32)
        by_place[s.order] = interval[source == j]
        out.append(by_place)
    return out


def repeated_windows(contexts: list[bytes], length: int, shard_bytes: int = 1 << 17) -> list[np.ndarray]:
    """For each context, the window starts (0..) whose string stands in another context as well."""
    shards, owners, at = [], [], 0
    for first, run in chunks(contexts, shard_bytes):
        sizes = np.fromiter(map(len, run), np.int64, len(run)) + 1
        raw = np.frombuffer(b"\n".join(run) + b"\n", np.uint8)
        ends = np.cumsum(sizes)
        text = raw.copy()
        text[ends - 1] = 255  # no UTF-8 byte
        start = ends - sizes
        counts = np.maximum(sizes - 1 - length + 1, 0)
        place = np.arange(counts.sum()) - np.repeat(np.cumsum(counts) - counts, counts)
        owners.append((np.repeat(np.arange(len(run)) + first, counts), place, place + np.repeat(start, counts)))
        shards.append(Shard(text, length))
        at += len(run)
    classes = merged_classes(shards, length)
    owner = np.concatenate([o for o, _, _ in owners])
    place = np.concatenate([p for _, p, _ in owners])
    kind = np.concatenate([c[i] for c, (_, _, i) in zip(classes, owners, strict=True)])
    times = np.bincount(kind) if len(kind) else np.zeros(0, np.int64)
    good = times[kind] > 1
    owner, place = owner[good], place[good]
    cut = np.searchsorted(owner, np.arange(len(contexts) + 1))
    return [place[a:b] for a, b in zip(cut[:-1], cut[1:], strict=True)]


def _stretches(places: np.ndarray, length: int) -> list[tuple[int, int]]:
    """Runs of bytes that windows at sorted places cover."""
    if not len(places):
        return []
    cuts = np.flatnonzero(np.diff(places) > length)
    return [(int(a), int(b) + length) for a, b in zip(places[np.concatenate(([0], cuts + 1))], places[np.append(cuts, len(places) - 1)], strict=True)]


#: Windows of a zone, and of the zones into which over-full cores are cut.
ZONES = (16, 4, 1)
_CONTEXT = "anchor long, again boolean, doc long, print long, start long, place int, context binary"
_ZONE = "core long, extent long, again boolean, doc long, print long, start long, first long, last long, place int"
_PIECE = "core long, over boolean, again boolean, doc long, print long, start long, place int, context binary"
_SPAN = "doc long, print long, start long, stop long"


def _cut_out(length: int):
    def run(batches):
        for b in batches:
            rows = []
            for doc, mark, text, wanted in zip(*(b.column(i).to_pylist() for i in range(4)), strict=True):
                for w in wanted:
                    p, hi, lo = w["place"] >> 16, w["place"] >> 8 & 255, w["place"] & 255
                    rows.append((w["anchor"], w["again"], doc, mark, p - hi, hi, text[p - hi : p - lo + length]))
            columns = list(zip(*rows, strict=True)) or [()] * 7
            types = (pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=["anchor", "again", "doc", "print", "start", "place", "context"])

    return run


def _zones(length: int, width: int):
    """Zones of contexts; core and extent hashes also tell the anchor and the zone's number."""

    def run(batches):
        for b in batches:
            anchor, doc, mark, start, hi = (b.column(k).to_numpy(zero_copy_only=False) for k in ("anchor", "doc", "print", "start", "place"))
            again = np.array(b.column("again").to_pylist(), bool)
            for at, some in chunks(b.column("context").to_pylist(), STRETCH):
                sizes = np.fromiter(map(len, some), np.int64, len(some))
                begin = np.cumsum(sizes) - sizes
                most = hi[at : at + len(some)].astype(np.int64)
                least = most - (sizes - length)
                n = most // width - least // width + 1
                own = np.repeat(np.arange(len(some)), n)
                zone = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(least // width, n)
                top, low = np.minimum(most[own], width * zone + width - 1), np.maximum(least[own], width * zone)
                raw = b"".join(some)
                origin = begin[own] + most[own]  # the anchor's place
                key = mix(anchor[at + own].view(U64) + zone.astype(U64))
                # the bytes of the zone's middle; a zone cut short at its context's border may hold some more in common
                core = _hashed(raw, origin - width * zone, origin - width * zone - width + 1 + length, key)
                extent = _hashed(raw, origin - top, origin - low + length, key)
                first = start[at + own] + most[own] - top
                yield pa.RecordBatch.from_arrays(
                    [_signed(core), _signed(extent), pa.array(again[at + own]), *(pa.array(x) for x in (doc[at + own], mark[at + own], start[at + own], first, first + top - low)), pa.array(top.astype(np.int32))],
                    names=["core", "extent", "again", "doc", "print", "start", "first", "last", "place"],
                )

    return run


def _pieces(length: int):
    def run(batches):
        for b in batches:
            rows = []
            for doc, mark, start, context, wanted in zip(*(b.column(k).to_pylist() for k in ("doc", "print", "start", "context", "wanted")), strict=True):
                rows += [(w["core"], w["over"], w["again"], doc, mark, w["first"], w["place"], context[w["first"] - start : w["last"] - start + length]) for w in wanted]
            columns = list(zip(*rows, strict=True)) or [()] * 8
            types = (pa.int64(), pa.bool_(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names=["core", "over", "again", "doc", "print", "start", "place", "context"])

    return run


def _merge(length: int, lot_bytes: int):
    """Streams pieces sorted by core in lots that hold all pieces of their cores."""

    def settle(rows):
        found = repeated_windows([r[4] for r in rows], length)
        spans = [(r[1], r[2], r[3] + a, r[3] + b) for r, places in zip(rows, found, strict=True) if not r[5] for a, b in _stretches(places, length)]
        columns = list(zip(*spans, strict=True)) or [()] * 4
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["doc", "print", "start", "stop"])

    def run(batches):
        rows, size = [], 0
        for b in batches:
            for r in zip(*(b.column(k).to_pylist() for k in ("core", "doc", "print", "start", "context", "again")), strict=True):
                if size > lot_bytes and r[0] != rows[-1][0]:
                    yield settle(rows)
                    rows, size = [], 0
                rows.append(r)
                size += len(r[4])
        if rows:
            yield settle(rows)

    return run


def repeated_spans(spark: SparkSession, rows: DataFrame, length: int, kinds_in_lot: int, lot_bytes: int) -> DataFrame:
    """doc, print, spans (start, stop in bytes; they may overlap) of every text with repeats. rows: doc, print, text (binary)."""
    seen = staged(spark, rows.mapInArrow(_find(length), _OCCURRENCE), "anchors")
    # counts are written before they are joined, so that the join's own shuffle can be split where one anchor or extent fills a task
    again = staged(spark, seen.groupBy("anchor").agg(F.count("*").alias("k")).where("k > 1").select("anchor"), "again")
    some = staged(spark, seen.join(again, "anchor"), "repeated")
    extents = staged(spark, some.groupBy("anchor", "extent").agg(F.count("*").alias("k"), F.min(F.struct("doc", "print", "place")).alias("one")), "extents")
    spans = some.join(extents.where("k > 1").select("anchor", "extent"), ["anchor", "extent"]).select(
        "doc", "print", (F.shiftright("place", 16) - (F.shiftright("place", 8).bitwiseAND(255))).alias("start"), (F.shiftright("place", 16) - F.col("place").bitwiseAND(255) + length).alias("stop")
    )
    # anchors with several surroundings
    kinds = extents.groupBy("anchor").agg(F.count("*").alias("kinds")).where("kinds > 1").select("anchor")
    open_ = extents.join(kinds, "anchor").select("anchor", (F.col("k") > 1).alias("again"), "one.*")
    wanted = open_.groupBy("doc", "print").agg(F.collect_list(F.struct("anchor", "again", "place")).alias("wanted"))
    contexts = staged(spark, rows.join(wanted, ["doc", "print"]).dropDuplicates(["doc", "print"]).select("doc", "print", "text", "wanted").mapInArrow(_cut_out(length), _CONTEXT), "contexts")
    for width in ZONES:
        zones = staged(spark, contexts.mapInArrow(_zones(length, width), _ZONE), "zones")
        alike = staged(spark, zones.groupBy("core", "extent").agg(F.count("*").alias("k"), F.min(F.struct("doc", "print", "start", "first", "last", "place", "again")).alias("one")), "alike")
        same = zones.where("NOT again").join(alike.where("k > 1").select("core", "extent"), ["core", "extent"]).select("doc", "print", F.col("first").alias("start"), (F.col("last") + length).alias("stop"))
        # a core none of whose zones is open any more needs no look at its windows
        settled = (F.col("k") > 1) | F.col("one.again")
        cores = alike.groupBy("core").agg(F.count("*").alias("kinds"), F.min(settled).alias("settled")).where("kinds > 1 AND NOT settled").select("core", (F.col("kinds") > kinds_in_lot).alias("over"))
        left = alike.join(cores, "core").select("core", "over", settled.alias("again"), "one.doc", "one.print", "one.start", "one.first", "one.last", "one.place")
        by_context = left.groupBy("doc", "print", "start").agg(F.collect_list(F.struct("core", "over", "again", "first", "last", "place")).alias("wanted"))
        pieces = staged(spark, contexts.join(by_context, ["doc", "print", "start"]).select("doc", "print", "start", "context", "wanted").mapInArrow(_pieces(length), _PIECE), "pieces")
        merged = pieces.where("NOT over").repartition("core").sortWithinPartitions("core").mapInArrow(_merge(length, lot_bytes), _SPAN)
        spans = spans.unionByName(same).unionByName(merged)
        contexts = pieces.where("over").select(F.col("core").alias("anchor"), "again", "doc", "print", "start", "place", "context")
        if contexts.isEmpty():
            break
    return spans.groupBy("doc", "print").agg(F.collect_set(F.struct("start", "stop")).alias("spans"))


def remove_repeats(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = 200, kinds_in_lot: int = 512, lot_bytes: int = 1 << 18) -> DataFrame:
    """docs with repeats cut from the text, plus _n_bytes, _n_removed, _n_spans and _kept_sha256 (of the bytes that stay).

    These four replace columns of docs that have their names."""
    if not GRAM < length <= GRAM + 208:
        raise ValueError(f"length must lie above {GRAM} and below {GRAM + 209}")
    marked = carried(docs, doc=F.coalesce(F.col(id_col).cast("long"), F.lit(-(1 << 63))), print=F.xxhash64(text_or_empty(text_col)), text=F.col(text_col))
    rows = marked.select("doc", "print", F.coalesce("text", F.lit("")).cast("binary").alias("text"))
    joined = marked.join(repeated_spans(spark, rows, length, kinds_in_lot, lot_bytes), ["doc", "print"], "left")

    @F.pandas_udf("struct<text string, n_bytes long, n_removed long, n_spans long, sha string>")
    def cut(text: pd.Series, spans: pd.Series) -> pd.DataFrame:
        out = []
        for t, found in zip(text, spans, strict=True):
            raw = (t or "").encode()
            kept, gone, runs, at = [], 0, 0, 0
            stop = -1
            for s in sorted((x["start"], x["stop"]) for x in found) if found is not None else ():
                if s[0] > stop:
                    kept.append(raw[at : s[0]])
                    runs += 1
                    gone += s[1] - s[0]
                else:
                    gone += max(0, s[1] - stop)
                stop = max(stop, s[1])
                at = stop
            stays = b"".join([*kept, raw[at:]]) if runs else raw
            out.append((t if not runs else stays.decode("utf-8", "ignore"), len(raw), gone, runs, hashlib.sha256(stays).hexdigest()))
        return pd.DataFrame(out, columns=["text", "n_bytes", "n_removed", "n_spans", "sha"])

    done = joined.select("row", cut("text", "spans").alias("cut"))
    return handed_back(done, docs, {text_col: "cut.text", "_n_bytes": "cut.n_bytes", "_n_removed": "cut.n_removed", "_n_spans": "cut.n_spans", "_kept_sha256": "cut.sha"})


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    done = remove_repeats(spark, table(spark, sf_dir, "documents").select("doc_id", "text"))
    return done.select("doc_id", F.col("_n_bytes").alias("n_bytes"), F.col("_n_removed").alias("n_removed"), F.col("_n_spans").alias("n_spans"), F.col("_kept_sha256").alias("kept_sha256"))


SQL = """
WITH raw AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x, octet_length(encode(coalesce(text, '')))::BIGINT AS n FROM documents),
windows AS (
  SELECT doc_id, s, md5_number(substr(x, 2 * s + 1, 400)) AS k
  FROM (SELECT doc_id, x, unnest(range(0, n - 199)) AS s FROM raw WHERE n >= 200)),
again AS (SELECT k FROM windows GROUP BY k HAVING count(*) > 1),
starts AS (SELECT doc_id, s FROM windows JOIN again USING (k)),
marked AS (SELECT doc_id, s, CASE WHEN s - lag(s) OVER (PARTITION BY doc_id ORDER BY s) <= 200 THEN 0 ELSE 1 END AS fresh FROM starts),
numbered AS (SELECT doc_id, s, sum(fresh) OVER (PARTITION BY doc_id ORDER BY s) AS run FROM marked),
runs AS (SELECT doc_id, run, min(s) AS a, max(s) + 200 AS b FROM numbered GROUP BY doc_id, run),
gaps AS (SELECT doc_id, run, a, b, coalesce(lag(b) OVER (PARTITION BY doc_id ORDER BY a), 0) AS before FROM runs),
told AS (
  SELECT r.doc_id, sum(b - a) AS gone, count(*) AS runs, string_agg(substr(x, 2 * before + 1, 2 * (a - before)), '' ORDER BY a) || substr(any_value(x), 2 * max(b) + 1) AS kept
  FROM gaps g JOIN raw r ON g.doc_id = r.doc_id GROUP BY r.doc_id)
SELECT r.doc_id, r.n AS n_bytes, coalesce(gone, 0)::BIGINT AS n_removed, coalesce(runs, 0)::BIGINT AS n_spans, sha256(unhex(coalesce(kept, x))) AS kept_sha256
FROM raw r LEFT JOIN told t ON r.doc_id = t.doc_id
"""
