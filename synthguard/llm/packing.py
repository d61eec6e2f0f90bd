"""Sum-of-squares online packing of tokenised documents into fixed windows.

A document's ids (and an end id) are cut into whole windows and a rest. The rest goes to the fill level that keeps the sum
over levels of squared counts of partially filled windows least; the counts stand in an array by level. Each task packs the
rows it reads as they come, so nothing is shuffled. When its rows end, the emptiest open windows are cut up to top off the
fullest, and the one that is left is split into runs whose lengths are powers of two, which need no padding.

Memory of a task: the ids of its open windows, of which there are fewer than window, each below window ids.

Tokenising: white space never lies within a token, so each distinct word of a batch is encoded once and its ids are copied
to every place where it stands.

Defined cases: null or empty text gives the end id alone; repeated rows are packed as often as they come; null ids of
documents are carried through; an empty table gives no rows; other columns are neither read nor returned.
"""

from __future__ import annotations

import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.taskcontext import TaskContext

from synthguard.llm.common import table
from synthguard.llm.textkernel import Words, as_bytes, chunks

_NAMES = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
_SCHEMA = ", ".join(f"{n} long" for n in _NAMES)


class CachedTokenizer:
    """Ids of many texts, each distinct word encoded once. Words are looked up by 64-bit hashes and their bytes compared with those
    that were encoded; a word whose hash is another word's is encoded on its own.

    New words are encoded in runs, with a mark between them that has an id of its own. Words that hold the mark once they are
    normalised, and runs whose ids do not have one mark between every two words, are encoded word by word.
    """

    MARK = "`"

    def __init__(self, path: str, most_words: int = 2_000_000, most_bytes: int = 1 << 26):
        from tokenizers import Tokenizer

        self.tokenizer, self.most_words, self.most_bytes = Tokenizer.from_file(path), most_words, most_bytes
        alone = self.tokenizer.encode(self.MARK, add_special_tokens=False).ids
        self.mark = alone[0] if len(alone) == 1 else None
        self._clear()

    def _clear(self):
        self.known, self.at, self.size = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.ids, self.used = np.zeros(1 << 16, np.uint32), 0
        self.word_at, self.word_size = np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.bytes, self.filled = np.zeros(1 << 18, np.uint8), 0

    def _has_mark(self, word: str) -> bool:
        """Whether the mark stands in the word as given or as normalised (NFC makes it of U+1FEF); of ASCII words only as given, a
        normaliser that makes it of those is told by the count of marks."""
        normalizer = self.tokenizer.normalizer
        return self.MARK in word or (normalizer is not None and not word.isascii() and self.MARK in normalizer.normalize_str(word))

    def _encoded(self, raw: list[bytes], run: int = 2000) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the words in a row, and how many each has."""
        words = [w.decode("utf-8", "replace") for w in raw]
        out = [np.zeros(0, np.uint32)] * len(words)
        plain = [] if self.mark is None else [i for i, w in enumerate(words) if not self._has_mark(w)]
        alone = set(range(len(words))).difference(plain)
        joint = f" {self.MARK} "
        for k in range(0, len(plain), run):
            lot = plain[k : k + run]
            ids = np.array(self.tokenizer.encode_batch_fast([joint.join([words[i] for i in lot])], add_special_tokens=False)[0].ids, np.uint32)
            cuts = np.flatnonzero(ids == self.mark)
            if len(cuts) != len(lot) - 1:
                alone.update(lot)
                continue
            for i, x, y in zip(lot, [0, *(cuts + 1).tolist()], [*cuts.tolist(), len(ids)], strict=True):
                out[i] = ids[x:y]
        for i in alone:
            out[i] = np.array(self.tokenizer.encode(words[i], add_special_tokens=False).ids, np.uint32)
        sizes = np.fromiter(map(len, out), np.int64, len(out))
        return (np.concatenate(out) if out else np.zeros(0, np.uint32)), sizes

    def _stored(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Where the ids of the words now stand, and how many each has."""
        ids, sizes = self._encoded(words)
        if self.used + len(ids) > len(self.ids):
            self.ids = np.concatenate((self.ids[: self.used], np.zeros(len(self.ids) + len(ids), np.uint32)))
        self.ids[self.used : self.used + len(ids)] = ids
        at = self.used + np.cumsum(sizes) - sizes
        self.used += len(ids)
        return at, sizes

    def _learn(self, hashes: np.ndarray, places: np.ndarray, words: list[bytes]) -> None:
        """hashes are sorted, and places tell where they go among the known."""
        at, sizes = self._stored(words)
        raw = np.frombuffer(b"".join(words), np.uint8)
        if self.filled + len(raw) > len(self.bytes):
            self.bytes = np.concatenate((self.bytes[: self.filled], np.zeros(len(self.bytes) + len(raw), np.uint8)))
        self.bytes[self.filled : self.filled + len(raw)] = raw
        long = np.fromiter(map(len, words), np.int64, len(words))
        word_at = self.filled + np.cumsum(long) - long
        self.filled += len(raw)
        put = lambda into, x: np.insert(into, places, x)
        self.known, self.at, self.size, self.word_at, self.word_size = put(self.known, hashes), put(self.at, at), put(self.size, sizes), put(self.word_at, word_at), put(self.word_size, long)

    def _same(self, buf: np.ndarray, start: np.ndarray, end: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Of the words buf[start:end] whether their bytes are those of the known words `at`."""
        long = end - start
        same = self.word_size[at] == long
        some = np.flatnonzero(same)
        n = long[some]
        first = np.cumsum(n) - n
        place = np.arange(n.sum())
        other = self.bytes[place + np.repeat(self.word_at[at[some]] - first, n)] != buf[place + np.repeat(start[some] - first, n)]
        if other.any():
            same[some[np.unique(np.searchsorted(first, np.flatnonzero(other), "right") - 1)]] = False
        return same

    def encode(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """All ids in a row, and how many each text has."""
        w = Words(texts, lower=False)
        return self._looked_up(w.buf, w.start, w.end, w.hashes(), w.first)

    def _looked_up(self, buf: np.ndarray, start: np.ndarray, end: np.ndarray, hashes: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the words buf[start:end]; bounds: each text's first word, and one past the last."""
        distinct, first, which = np.unique(hashes, return_index=True, return_inverse=True)
        if len(self.known) > self.most_words or self.filled > self.most_bytes:
            self._clear()
        at = np.searchsorted(self.known, distinct)
        new = np.ones(len(distinct), bool)
        inside = at < len(self.known)
        new[inside] = self.known[at[inside]] != distinct[inside]
        cut = lambda words: [buf[a:b].tobytes() for a, b in zip(start[words].tolist(), end[words].tolist(), strict=True)]
        if new.any():
            self._learn(distinct[new], at[new], cut(first[new]))
            at = np.searchsorted(self.known, distinct)
        at = at[which]
        size, place = self.size[at], self.at[at]
        odd = np.flatnonzero(~self._same(buf, start, end, at)) if len(at) else at
        if len(odd):  # their hashes are those of other words
            place[odd], size[odd] = self._stored(cut(odd))
        ends = np.cumsum(size)
        total = int(ends[-1]) if len(ends) else 0
        # place of every id: its word's place in the store plus its rank in the word
        ids = self.ids[np.arange(total) + np.repeat(place - (ends - size), size)]
        before = np.concatenate(([0], ends))
        return ids, np.diff(before[bounds])


@lru_cache(maxsize=1)
def tokenizer_for(path: str) -> CachedTokenizer:
    """One for each Python worker, so that later tasks find the words of earlier ones."""
    return CachedTokenizer(path)


class Packer:
    """Open windows by fill level, and the count of them at each level."""

    def __init__(self, window: int, number: int):
        self.window, self.levels, self.open = window, np.zeros(window + 1, np.int64), {}
        self.next_id, self.out = number, []

    def _emit(self, pieces) -> None:
        offset = 0
        for doc, start, ids, tokens in pieces:
            self.out.append((doc, start, len(ids), zlib.crc32(ids.astype("<u4", copy=False).tobytes()), tokens, self.next_id, offset))
            offset += len(ids)
        self.next_id += 1

    def level_for(self, size: int) -> int:
        """The level (0: a new window) whose choice raises the sum of squared counts least; ties go to the fullest."""
        n, c = self.levels, self.window
        # leaving level h takes 2 n(h) - 1 off, reaching level h + size adds 2 n(h + size) + 1; full windows aren't counted
        cost = np.where(n[: c - size + 1] > 0, 1 - 2 * n[: c - size + 1], np.iinfo(np.int32).max)
        cost[0] = 0
        cost[: c - size] += 2 * n[size:c] + 1
        return int(c - size - np.argmin(cost[::-1]))

    def add(self, doc, ids: np.ndarray) -> None:
        whole = len(ids) // self.window * self.window
        for k in range(0, whole, self.window):
            self._emit([(doc, k, ids[k : k + self.window], len(ids))])
        if whole == len(ids):
            return
        size = len(ids) - whole
        level = self.level_for(size)
        pieces = []
        if level:
            pieces = self.open[level].pop()
            self.levels[level] -= 1
        pieces.append((doc, whole, ids[whole:].copy(), len(ids)))
        if level + size == self.window:
            self._emit(pieces)
        else:
            self.open.setdefault(level + size, []).append(pieces)
            self.levels[level + size] += 1

    def close(self) -> None:
        """Cuts the emptiest open windows to fill the fullest; the last one is split at powers of two."""
        left = [(k, p) for k in sorted(self.open, reverse=True) for p in self.open[k]]
        stock: list = []  # pieces of windows that were taken apart
        while left or stock:
            fill, pieces = left.pop(0) if left else (0, [])
            room = self.window - fill
            while room and (stock or left):
                if not stock:
                    stock = left.pop()[1]
                doc, start, ids, tokens = stock.pop()
                if len(ids) > room:
                    stock.append((doc, start + room, ids[room:], tokens))
                    ids = ids[:room]
                pieces = [*pieces, (doc, start, ids, tokens)]
                room -= len(ids)
            if not room:
                self._emit(pieces)
                continue
            fill = self.window - room
            while fill:
                take = 1 << (fill.bit_length() - 1)
                fill -= take
                run = []
                while take:
                    doc, start, ids, tokens = pieces.pop(0)
                    if len(ids) > take:
                        pieces.insert(0, (doc, start + take, ids[take:], tokens))
                        ids = ids[:take]
                    run.append((doc, start, ids, tokens))
                    take -= len(ids)
                self._emit(run)
        self.open, self.levels = {}, np.zeros(self.window + 1, np.int64)

    def flush(self) -> pa.RecordBatch:
        columns = list(zip(*self.out, strict=True)) or [()] * len(_NAMES)
        self.out = []
        return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=_NAMES)


def pack(docs: DataFrame, tokenizer_path: str, id_col: str = "doc_id", text_col: str = "text", window: int = 4096, end_id: int = 2) -> DataFrame:
    """One row for each piece of a document: where it starts, how long it is, and its window and place there."""

    def run(batches):
        tokenizer = tokenizer_for(tokenizer_path)
        packer = Packer(window, TaskContext.get().partitionId() << 40)
        for b in batches:
            ids_of, texts = b.column(0).to_pylist(), as_bytes(b.column(1))
            for at, run_of in chunks(texts):
                ids, sizes = tokenizer.encode(run_of)
                stops = np.cumsum(sizes)
                for i, (stop, size) in enumerate(zip(stops.tolist(), sizes.tolist(), strict=True)):
                    packer.add(ids_of[at + i], np.append(ids[stop - size : stop], np.uint32(end_id)))
            yield packer.flush()
        packer.close()
        yield packer.flush()

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, _SCHEMA)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
