"""SentencePiece encoding and decoding by suffix-array matching.

Texts fall into units (spaces and what follows them) across which no piece reaches. The distinct units of a batch that
were not met before are concatenated and their suffixes ordered; each piece of the vocabulary is looked up by binary
search, which gives the range of all its occurrences; the occurrences, sorted by position, are the edges of a lattice. The
lattice is relaxed as the model's merges demand: the adjacent pair of segments whose edge has the best score in its unit (the
leftmost of equals) becomes one segment, until no pair has an edge; pairs that nothing can touch before their turn are joined
in the same round. What is left without a piece falls back to its bytes. A best-path relaxation by summed scores would be the unigram model's; this vocabulary is of the merging kind, so the
result here equals the library's.

Defined cases: null and empty texts have no ids; repeated rows are encoded alike; null ids of documents are carried
through; an empty table gives no rows; other columns are not read. Control pieces are never produced from text.
"""

from __future__ import annotations

import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from synthguard.llm.common import table
from synthguard.llm.packing import CachedTokenizer
from synthguard.llm.suffix_dedup import suffix_order
from synthguard.llm.textkernel import as_bytes, chunks, span_hash

MARK = "▁".encode()  # stands for a space


class PieceCoder(CachedTokenizer):
    def __init__(self, path: str, most_words: int = 1_000_000, most_bytes: int = 1 << 26):
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        self.most_words, self.most_bytes = most_words, most_bytes
        n = sp.get_piece_size()
        plain = [i for i in range(n) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))]
        self.byte_ids = np.full(256, sp.unk_id(), np.uint32)
        for i in range(n):
            if sp.is_byte(i):
                self.byte_ids[int(sp.id_to_piece(i)[3:5], 16)] = i
        self.text_of = {i: sp.id_to_piece(i).encode().replace(MARK, b" ") for i in plain} | {int(i): bytes([b]) for b, i in enumerate(self.byte_ids) if sp.is_byte(int(i))}
        raw = [sp.id_to_piece(i).encode() for i in plain]
        if any(MARK in p.lstrip(MARK) for p in (x[len(x) - len(x.lstrip(MARK)) :] for x in raw)):
            raise ValueError("a piece reaches across a space")
        self.width = max(map(len, raw))
        self.pieces = np.array(raw, f"S{self.width}")
        self.above = np.array([p + b"\xff" * (self.width - len(p)) for p in raw], f"S{self.width}")
        self.sizes = np.fromiter(map(len, raw), np.int64, len(raw))
        self.piece_ids = np.array(plain, np.uint32)
        self.costs = -np.array([sp.get_score(i) for i in plain])
        held = np.zeros(256, bool)
        held[np.frombuffer(b"".join(raw), np.uint8)] = True
        self.alone = ~held  # ASCII characters that no piece holds are units of their own
        self.alone[128:] = False
        self.alone[32] = False
        self._clear()

    def edges(self, text: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(start << 8 | length, index of the piece) of all occurrences of all pieces, sorted by position."""
        text = np.where(text == 0, np.uint8(255), text)  # no piece holds either, and numpy drops zeros at the end of a string
        order = suffix_order(text, self.width)
        padded = np.concatenate((text, np.full(self.width, 255, np.uint8)))
        keys = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(padded, self.width)[order]).view(f"S{self.width}").ravel()
        # rotations agree with suffixes up to the padding at the very end
        if len(keys) > 1 and not (keys[1:] >= keys[:-1]).all():
            fix = np.argsort(keys, kind="stable")
            keys, order = keys[fix], order[fix]
        low, high = np.searchsorted(keys, self.pieces, "left"), np.searchsorted(keys, self.above, "right")
        n = high - low
        piece = np.repeat(np.arange(len(n)), n)
        place = order[np.arange(n.sum()) + np.repeat(low - (np.cumsum(n) - n), n)]
        key = place << 8 | self.sizes[piece]
        by_place = np.argsort(key, kind="stable")
        return key[by_place], piece[by_place]

    def _encoded(self, raw: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        units = [u.replace(b" ", MARK) for u in raw]
        text = np.frombuffer(b"".join(units), np.uint8)
        sizes = np.fromiter(map(len, units), np.int64, len(units))
        keys, found = self.edges(text)

        def edge(start, stop):
            at = np.minimum(np.searchsorted(keys, k := start << 8 | np.minimum(stop - start, 255)), max(len(keys) - 1, 0))
            return np.where((keys[at] == k) & (stop - start < 256), found[at], -1) if len(keys) else np.full(len(start), -1)

        start, stop = self._relaxed(text, np.cumsum(sizes), keys, found)
        order = np.argsort(start)
        start, stop = start[order], stop[order]
        piece = edge(start, stop)
        # a segment without a piece becomes its bytes
        count = np.where(piece >= 0, 1, stop - start)
        at = np.repeat(start - (np.cumsum(count) - count), count) + np.arange(count.sum())
        ids = np.where(np.repeat(piece >= 0, count), self.piece_ids[np.repeat(np.maximum(piece, 0), count)], self.byte_ids[text[np.minimum(at, len(text) - 1)]] if len(text) else np.zeros(0, np.uint32))
        ends = np.cumsum(sizes)
        owner = np.searchsorted(ends, start, "right")
        return ids.astype(np.uint32), np.bincount(owner, count, len(units)).astype(np.int64)

    def _relaxed(self, text: np.ndarray, ends: np.ndarray, keys: np.ndarray, found: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Starts and stops of the segments that are left when every unit's best edge over two segments has been taken, one after the other.

        A round takes, beside each unit's best pair, every pair that cannot be touched before its turn: no edge over other
        segments that crosses its borders has a score as good, and of pairs alike in score that overlap every other one counts,
        from the left. Borders that no edge crosses any more part units, and units without a pair are done, so long units of
        any kind take few rounds over what is left of them.
        """
        start = np.flatnonzero((text & 0xC0) != 0x80)
        stop = np.append(start[1:], len(text))
        last = np.isin(stop, ends)  # segments that end a unit
        number = np.full(len(text) + 1, -1)
        number[start] = np.arange(len(start))
        number[len(text)] = len(start)
        left, right, cost = number[keys >> 8], number[(keys >> 8) + (keys & 255)], self.costs[found]
        in_unit = np.cumsum(last) - last
        ok = (left >= 0) & (right > left + 1)
        ok[ok] = in_unit[left[ok]] == in_unit[right[ok] - 1]
        left, right, cost = left[ok], right[ok], cost[ok]
        done = []
        while len(left):
            n = len(start)
            pair = np.full(n, np.inf)  # of a segment and the next
            two = right - left == 2
            pair[left[two]] = cost[two]
            # the best edge over three segments or more across each border; border k lies in front of segment k
            across = np.full(n + 1, np.inf)
            a, z, c = left[~two], right[~two], cost[~two]
            for step in range(1, int((z - a).max(initial=1))):
                inner = a + step < z
                np.minimum.at(across, a[inner] + step, c[inner])
            joined = np.minimum(across[1:], pair)  # border behind a segment
            last |= np.isinf(joined)
            unit = np.cumsum(last) - last
            first = np.flatnonzero(np.concatenate(([True], last[:-1])))
            least = np.minimum.reduceat(pair, first)
            live = np.isfinite(least)[unit]
            done.append((start[~live], stop[~live]))
            best = np.flatnonzero(live & (pair == least[unit]))
            best = best[np.concatenate(([True], unit[best][1:] != unit[best][:-1]))]
            before, after = np.concatenate(([np.inf], pair[:-1])), np.append(pair[1:], np.inf)
            calm = np.isfinite(pair) & (np.minimum(across[:-1], np.append(across[2:], np.inf)) > pair) & (before >= pair) & (after >= pair)
            # runs of overlapping pairs alike in score; a run behind a pair like them that may go first waits
            opens = calm & ~(np.concatenate(([False], calm[:-1])) & (before == pair))
            origin = np.maximum.accumulate(np.where(opens, np.arange(n), 0))
            taken = calm & (before[origin] > pair) & ((np.arange(n) - origin) % 2 == 0)
            taken[best] = True
            gone = np.concatenate(([False], taken[:-1]))
            stop = stop.copy()
            stop[taken] = stop[np.flatnonzero(taken) + 1]
            last[taken] = last[np.flatnonzero(taken) + 1]
            stays = live & ~gone
            number = np.append(np.where(stays, np.cumsum(stays) - 1, -1), 0)
            # an edge lives while segments start and end where it does, and it covers two of them at least
            opened, closed = number[left], number[right - 1]
            closed = np.where(gone[right - 1], number[right - 2], closed)
            ok = (opened >= 0) & (closed > opened) & ~taken[right - 1]
            left, right, cost = opened[ok], closed[ok] + 1, cost[ok]
            start, stop, last = start[stays], stop[stays], last[stays]
        done.append((start, stop))
        start, stop = (np.concatenate(x) for x in zip(*done, strict=True))
        return start, stop

    def encode(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        full = [b" " + t.replace(MARK, b" ") if t else b"" for t in texts]
        sizes = np.fromiter(map(len, full), np.int64, len(full))
        buf = np.frombuffer(b"".join(full), np.uint8)
        begin = np.concatenate(([0], np.cumsum(sizes)))
        if not len(buf):
            return np.zeros(0, np.uint32), np.zeros(len(texts), np.int64)
        space, alone = buf == 32, self.alone[buf]
        new = np.zeros(len(buf), bool)
        new[1:] = (space[1:] & ~space[:-1]) | alone[1:] | alone[:-1]
        new[begin[:-1][sizes > 0]] = True
        start = np.flatnonzero(new)
        end = np.append(start[1:], len(buf))
        return self._looked_up(buf, start, end, span_hash(buf, start, end), np.searchsorted(start, begin))

    def decode(self, ids) -> str:
        raw = b"".join(self.text_of.get(int(i), b"") for i in ids)
        return raw.removeprefix(b" ").decode("utf-8", "replace")


@lru_cache(maxsize=1)
def coder_for(path: str) -> PieceCoder:
    """One for each Python worker, so that later tasks find the units of earlier ones."""
    return PieceCoder(path)


def encode(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids, decodes: every text's ids, and whether they give the text back."""

    def run(batches):
        coder = coder_for(model_path)
        for b in batches:
            texts = as_bytes(b.column(1))
            lists, same = [], []
            for _, some in chunks(texts):
                ids, sizes = coder.encode(some)
                ends = np.cumsum(sizes)
                for t, e, n in zip(some, ends.tolist(), sizes.tolist(), strict=True):
                    own = ids[e - n : e]
                    lists.append(own.astype(np.int32))
                    same.append(coder.decode(own).encode() == t)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(lists, pa.list_(pa.int32())), pa.array(same, pa.bool_())], names=["doc_id", "ids", "decodes"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, "doc_id long, ids array<int>, decodes boolean")


def decode(encoded: DataFrame, model_path: str, ids_col: str = "ids") -> DataFrame:
    """encoded with `text`: the texts of its ids (null for null)."""

    @F.pandas_udf("string")
    def told(ids):
        coder = coder_for(model_path)
        return ids.map(lambda x: None if x is None else coder.decode(x))

    return encoded.withColumn("text", told(F.col(ids_col)))


def checksum(ids) -> int:
    return zlib.crc32(np.asarray(ids, "<u4").tobytes())


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    done = encode(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))
    return done.select("doc_id", F.size("ids").cast("long").alias("n_ids"), "ids", "decodes")
