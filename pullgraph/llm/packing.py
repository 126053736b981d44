"""Sum-of-squares online packing of documents into token windows.

Each scan task packs its own stream of documents.  A document longer than a window first gives whole windows; what
remains, of size s, goes to the open window level h (or a new window) that minimises the sum of squared counts of
partially filled windows: moving a window from level h to h + s changes that sum by counts alone, so a level array
decides without looking at single windows.  A window that becomes full is written at once.

Open windows hold OPEN_TOKENS tokens and OPEN_PIECES pieces at most.  When either is reached, and at the end of the task,
they are settled by cutting: the fullest are kept and filled up with pieces of the emptiest, which leaves less than a
window of room.  What is left at the end is cut into full windows and ones whose sizes are powers of two, which need no
padding.

Tasks share nothing, so nothing is shuffled; memory is one slice of texts and the open windows, whatever the task holds.
"""

from __future__ import annotations

import re
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession

from .common import U64, Words, arrow_map, batches, documents_of, held_by, numbered, slice_identity, table

WINDOW = 2048
#: Tokens and pieces in open windows of a task at most; with either, open windows are settled.
OPEN_TOKENS, OPEN_PIECES = 2 << 20, 100_000
#: Distinct parts and their ids that a worker keeps, 36 bytes besides the part's own and 4 bytes each; beyond either, the
#: table starts anew.
CACHE_PARTS, CACHE_IDS = 2_500_000, 16_000_000
#: Parts that may stay in a worker after a task.
KEPT_PARTS = 600_000
#: sequence_id = task * SEQUENCES + number within the task.
SEQUENCES = 1 << 40

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


#: Letters whose lower case is one letter, and signs that are words of their own after letters.
LETTERS = "A-Za-zÀ-ÖØ-öø-ÿ"
STOPS = b".,;:!?"


class WordTokenizer:
    """Ids of whole texts by a tokenizer whose words never reach across white space.

    Its normaliser only recomposes characters, lower-cases and folds white space, and its splitter drops white space and
    never joins letters with other signs but apostrophes.  So a text's ids are those of its parts, one after another: what
    stands between ASCII white space, with stops after a letter as a part of their own.  Parts are told apart by their bytes
    with ASCII letters in lower case: a sorted table of hashes finds those seen before, whose bytes are then compared; only
    new parts become strings and go to the tokenizer.  A text with one of the tokenizer's special strings goes to it whole.
    """

    def __init__(self, path: str) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.special = [t.content.lower() for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.plain = re.compile(f"[{LETTERS}]+").fullmatch
        # A run of letters is one word, and the last token of each word carries the end mark.
        vocabulary = self.tokenizer.get_vocab(with_added_tokens=False)
        self.ends = np.zeros(max(self.tokenizer.get_vocab(with_added_tokens=True).values()) + 1, bool)
        self.ends[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        self.stop = np.zeros(256, bool)
        self.stop[list(STOPS)] = True
        self._clear()

    def _clear(self) -> None:
        self.hash, self.row = np.zeros(0, U64), np.zeros(0, np.int32)  # sorted hashes, and the row of each
        self.at, self.n = np.zeros(0, np.int64), np.zeros(0, np.int32)  # per row: its place in flat, and its length
        self.flat, self.used = np.zeros(1 << 16, "<u4"), 0
        self.from_, self.size = np.zeros(0, np.int64), np.zeros(0, np.int32)  # per row: where its bytes are, and how many
        self.bytes, self.written = np.zeros(1 << 16, np.uint8), 0

    def trim(self) -> None:
        """What stays between tasks of a worker: a table of moderate size, or none."""
        if len(self.n) > KEPT_PARTS:
            self._clear()

    def _encode(self, parts: list[str]) -> list[np.ndarray]:
        """Ids of each part; letter runs go many at a time, and their ids are cut at the ends of words."""
        out: list = [None] * len(parts)
        plain = [i for i, p in enumerate(parts) if self.plain(p)]
        for k in range(0, len(plain), 256):
            some = plain[k : k + 256]
            ids = np.array(self.tokenizer.encode(" ".join([parts[i] for i in some]), add_special_tokens=False).ids, "<u4")
            stops = (np.flatnonzero(self.ends[ids]) + 1).tolist()
            for i, x, y in zip(some, [0, *stops], stops, strict=False):
                out[i] = ids[x:y]
        for i, p in enumerate(parts):
            if out[i] is None:
                out[i] = np.array(self.tokenizer.encode(p, add_special_tokens=False).ids, "<u4")
        return out

    def _learn(self, hashes: np.ndarray, parts: list[bytes]) -> np.ndarray:
        """Rows of new parts; of those that share a hash, one alone can be found again."""
        ids = self._encode([x.decode("utf-8", "replace") for x in parts])
        n, size = np.array([len(x) for x in ids], np.int32), np.array([len(x) for x in parts], np.int32)
        first, total, width = len(self.n), int(n.sum()), int(size.sum())
        if self.used + total > len(self.flat):
            self.flat = np.concatenate([self.flat[: self.used], np.zeros(self.used + total, "<u4")])
        if self.written + width > len(self.bytes):
            self.bytes = np.concatenate([self.bytes[: self.written], np.zeros(self.written + width, np.uint8)])
        if total:
            self.flat[self.used : self.used + total] = np.concatenate(ids)
        self.bytes[self.written : self.written + width] = np.frombuffer(b"".join(parts), np.uint8)
        self.at = np.concatenate([self.at, self.used + np.cumsum(n) - n])
        self.n = np.concatenate([self.n, n])
        self.from_ = np.concatenate([self.from_, self.written + np.cumsum(size) - size])
        self.size = np.concatenate([self.size, size])
        self.used, self.written = self.used + total, self.written + width
        rows = np.arange(first, first + len(n), dtype=np.int32)
        hashes, one = np.unique(hashes, return_index=True)
        place = np.searchsorted(self.hash, hashes)
        fresh = np.ones(len(hashes), bool)
        if len(self.hash):
            fresh = self.hash[np.minimum(place, len(self.hash) - 1)] != hashes
        self.hash, self.row = np.insert(self.hash, place[fresh], hashes[fresh]), np.insert(self.row, place[fresh], rows[one[fresh]])
        return rows

    def _find(self, hashes: np.ndarray, parts: pa.Array) -> np.ndarray:
        """Row of each of the distinct parts, -1 where it is new; the hash finds it and the bytes decide."""
        if not len(self.hash):
            return np.full(len(parts), -1, np.int64)
        place = np.minimum(np.searchsorted(self.hash, hashes), len(self.hash) - 1)
        offsets = np.frombuffer(parts.buffers()[1], np.int64, len(parts) + 1)
        size, row = np.diff(offsets), self.row[place].astype(np.int64)
        known = np.flatnonzero((self.hash[place] == hashes) & (self.size[row] == size))
        n = size[known]
        inside = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        data = np.frombuffer(parts.buffers()[2], np.uint8) if len(inside) else np.zeros(0, np.uint8)
        differ = data[np.repeat(offsets[known], n) + inside] != self.bytes[np.repeat(self.from_[row[known]], n) + inside]
        out = np.full(len(parts), -1, np.int64)
        out[known] = row[known]
        out[known[np.repeat(np.arange(len(known)), n)[differ]]] = -1
        return out

    def _parts(self, w: Words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(start, stop, text number) of the parts: words without stops that follow a letter, then those stops."""
        data = w.data
        solid = np.maximum.accumulate(np.where(self.stop[data], -1, np.arange(len(data))))
        cut = solid[w.stop - 1] + 1  # end of the word without trailing stops
        last, before = data[np.maximum(cut - 1, 0)], data[np.maximum(cut - 2, 0)]
        letter = ((last >= 97) & (last <= 122)) | ((last >= 0x80) & (last != 0x97) & (last != 0xB7) & (before == 0xC3))
        cut = np.where((cut > w.start) & letter, cut, w.stop)
        start, stop = np.stack([w.start, cut], axis=1).ravel(), np.stack([cut, w.stop], axis=1).ravel()
        there = start < stop
        return start[there], stop[there], np.repeat(np.repeat(np.arange(len(w.n)), w.n), 2)[there]

    def ids(self, texts: list[str]) -> list[bytes]:
        """Little-endian unsigned 32-bit ids of each text."""
        whole = {}
        for i, t in enumerate(texts):
            low = t.lower() if "<" in t or any("<" not in x for x in self.special) else ""
            if any(x in low for x in self.special):
                whole[i] = np.array(self.tokenizer.encode(t, add_special_tokens=False).ids, "<u4").tobytes()
        out = self._ids(["" if i in whole else t for i, t in enumerate(texts)])
        return [whole.get(i, x) for i, x in enumerate(out)]

    def _ids(self, texts: list[str]) -> list[bytes]:
        w = Words(texts, lower_ascii=True)
        if not len(w.start):
            return [b""] * len(texts)
        start, stop, owner = self._parts(w)
        back, parts = numbered(w.data, start, stop)
        offsets = np.frombuffer(parts.buffers()[1], np.int64, len(parts) + 1)
        hashes = slice_identity(np.frombuffer(parts.buffers()[2], np.uint8), offsets[:-1], offsets[1:])
        found = self._find(hashes, parts)
        new = np.flatnonzero(found < 0)
        if len(new):
            raw = parts.buffers()[2].to_pybytes()
            found[new] = self._learn(hashes[new], [raw[x:y] for x, y in zip(offsets[new].tolist(), offsets[new + 1].tolist(), strict=True)])
        row = found[back]
        n = self.n[row].astype(np.int64)
        ends = np.cumsum(n)
        flat = self.flat[np.repeat(self.at[row] - (ends - n), n) + np.arange(int(ends[-1]))].tobytes()
        bounds = np.concatenate([[0], ends])[np.searchsorted(owner, np.arange(len(texts) + 1))].tolist()
        if len(self.n) > CACHE_PARTS or self.used > CACHE_IDS:
            self._clear()
        return [flat[4 * x : 4 * y] for x, y in zip(bounds, bounds[1:], strict=False)]


@held_by(__name__)
@lru_cache(maxsize=4)
def word_tokenizer(path: str) -> WordTokenizer:
    return WordTokenizer(path)


class Packer:
    """One task's windows.  A piece is (doc_id, start, ids, doc_tokens)."""

    def __init__(self, window: int = WINDOW, open_tokens: int = OPEN_TOKENS, open_pieces: int = OPEN_PIECES) -> None:
        self.window, self.most = window, (max(open_tokens, 2 * window), max(open_pieces, 2))
        self._empty()

    def _empty(self) -> None:
        self.count = np.zeros(self.window + 1, np.int64)  # open windows by fill level
        self.open: list[list[list[tuple]]] = [[] for _ in range(self.window + 1)]
        self.tokens = self.pieces = 0  # in open windows

    def add(self, doc_id: int | None, ids: bytes) -> list[list[tuple]]:
        """Place one document; returns the windows that became full."""
        w, total, done = self.window, len(ids) // 4, []
        whole = total // w
        for k in range(whole):
            done.append([(doc_id, k * w, ids[4 * k * w : 4 * (k + 1) * w], total)])
        s = total - whole * w
        if s == 0:
            return done
        piece = (doc_id, whole * w, ids[4 * whole * w :], total)
        n = self.count
        # Change of the sum of squares when a window leaves level h and joins level h + s (a full window counts no more).
        gain = 2 * n[s : w + 1] + 1
        gain[-1] = 0
        gain[1:] -= 2 * n[1 : w - s + 1] - 1
        usable = n[: w - s + 1] > 0
        usable[0] = True
        h = int(np.argmin(np.where(usable, gain, np.iinfo(np.int64).max)))
        held = []
        if h:
            held = self.open[h].pop()
            n[h] -= 1
        held.append(piece)
        if h + s == w:
            done.append(held)
            self.tokens, self.pieces = self.tokens - h, self.pieces - (len(held) - 1)
        else:
            self.open[h + s].append(held)
            n[h + s] += 1
            self.tokens, self.pieces = self.tokens + s, self.pieces + 1
            if self.tokens > self.most[0] or self.pieces > self.most[1]:
                done += self.settle()
        return done

    def settle(self) -> list[list[tuple]]:
        """Fill the fullest open windows with cuts of the emptiest; what does not fill a window stays open."""
        w = self.window
        levels = [(h, held) for h in range(w, 0, -1) for held in self.open[h]]
        total = sum(h for h, _ in levels)
        keep = -(-total // w)
        donors = [p for _, held in levels[keep:] for p in held]
        out = []
        for h, held in levels[:keep]:
            room = w - h
            while room and donors:
                doc_id, start, ids, n = donors.pop()
                take = min(room, len(ids) // 4)
                held.append((doc_id, start, ids[: 4 * take], n))
                if 4 * take < len(ids):
                    donors.append((doc_id, start + take, ids[4 * take :], n))
                room -= take
            out.append((w - room, held))
        self._empty()
        for h, held in out:
            if h < w:
                self.open[h].append(held)
                self.count[h] += 1
                self.tokens, self.pieces = self.tokens + h, self.pieces + len(held)
        return [held for h, held in out if h == w]

    def close(self) -> list[list[tuple]]:
        """settle(), with what is left cut into full windows and windows whose sizes are powers of two."""
        done = self.settle()
        rest = [p for level in self.open for held in level for p in held][::-1]
        left = self.tokens
        self._empty()
        while left:
            room, held = min(self.window, 1 << (left.bit_length() - 1)), []
            left -= room
            while room:
                doc_id, start, ids, n = rest.pop()
                take = min(room, len(ids) // 4)
                held.append((doc_id, start, ids[: 4 * take], n))
                if 4 * take < len(ids):
                    rest.append((doc_id, start + take, ids[4 * take :], n))
                room -= take
            done.append(held)
        return done


def pack(docs: DataFrame, tokenizer_path: str, window: int = WINDOW, end_id: int = 1, with_ids: bool = False) -> DataFrame:
    """Pieces of all documents: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset (and ids).

    Ids are the library's own, special strings included.  Null text: empty, so the document is its end id alone.  Rows that repeat are packed as often as they occur, a null
    doc_id is kept.  Extra columns are dropped.  An empty table has no pieces.  A document of any length is cut into
    whole windows, so no size is special.
    """

    def rows(windows, task, number):
        out = []
        for held in windows:
            offset = 0
            for doc_id, start, ids, n in held:
                out.append((doc_id, start, len(ids) // 4, zlib.crc32(ids), n, task * SEQUENCES + number, offset, ids))
                offset += len(ids) // 4
            number += 1
        return out, number

    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]

    def emit(out):
        cols = list(zip(*out, strict=True)) if out else [[] for _ in range(8)]
        arrays = [pa.array(c, pa.int64()) for c in cols[:7]]
        if with_ids:
            arrays.append(pa.array([np.frombuffer(x, "<u4").astype(np.int64) for x in cols[7]], pa.list_(pa.int64())))
        return pa.RecordBatch.from_arrays(arrays, names + ["ids"] * with_ids)

    def run(it):
        tok, packer, task, number = word_tokenizer(tokenizer_path), Packer(window), TaskContext.get().partitionId(), 0
        end = np.array([end_id], "<u4").tobytes()
        for b in batches(it, 2 << 20):
            done = []
            for doc_id, ids in zip(b.column(0).to_pylist(), tok.ids([t or "" for t in b.column(1).to_pylist()]), strict=True):
                done += packer.add(doc_id, ids + end)
            out, number = rows(done, task, number)
            yield emit(out)
        tok.trim()
        out, number = rows(packer.close(), task, number)
        yield emit(out)

    return arrow_map(documents_of(docs), run, PIECES + ", ids array<long>" * with_ids)


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
