"""SentencePiece (merge-type) encoding and decoding with a prefix table.

Merging pairs by score has a property that makes a linear scan possible: every prefix of a text has exactly one
encoding, and the encoding of a prefix minus its last token is again the encoding of that shorter prefix.  So one value
per prefix, its last token, describes all of them.  The scan finds all pieces that end at a position with a string
automaton, and keeps the one that may follow the last token of the prefix before it; ids are then read off backwards.

Whether token b may follow token a is a property of the pair alone: a, b stays as it is when the pair is encoded by
itself.  `Merges.compatible` decides that from how each of the two was built, and remembers the answer.

Pieces hold the space mark only at their start, so a text falls into independent chunks at every space mark that
follows another character; chunks repeat, and each worker keeps a bounded two-generation table of chunks seen.

Texts are taken as they are, with one space mark put before them, as the model's normaliser does; a model with another one
is refused when it is loaded, where PROBES are compared with the library.
"""

from __future__ import annotations

import hashlib
import re
from functools import lru_cache

import ahocorasick
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame, SparkSession

from .common import arrow_map, batches, documents_of, held_by, table

SPACE_MARK = "▁"
#: Chunks kept per generation in each worker.
CACHE = 400_000
#: Texts that other normalisers, or none of a space put first, would change.
PROBES = ("", " ", "  two  spaces ", "Ａｂ ① ﬁ e\u0301 é", "a\tb\r\nc\u00a0d\u3000e", "x\u0000y\u200b \ufeff", "UPPER lower ▁ 12")
#: Longer chunks are encoded each time and not kept.
LONGEST_KEPT = 64


class Merges:
    """Vocabulary, automaton and pair rule of one merge-type model with byte fallback."""

    def __init__(self, path: str) -> None:
        model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.piece: list[str] = [model.id_to_piece(i) for i in range(model.get_piece_size())]
        self.byte: dict[int, int] = {int(self.piece[i][3:5], 16): i for i in range(len(self.piece)) if model.is_byte(i)}
        self.byte_of = {i: x for x, i in self.byte.items()}
        plain = [i for i in range(len(self.piece)) if not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))]
        self.id = {self.piece[i]: i for i in plain}
        if any(SPACE_MARK in p.lstrip(SPACE_MARK) for p in self.id):
            raise ValueError("a piece holds a space mark after another character; chunks would not be independent")
        # Runs of space marks share one score, so their order of merging is by place; they are handled apart.
        self.runs = {len(p) for p in self.id if p == SPACE_MARK * len(p)}
        words = [p for p in self.id if not p.startswith(SPACE_MARK * 2)]
        order = sorted((p for p in words if len(p) > 1), key=lambda p: -model.get_score(self.id[p]))
        if len({model.get_score(self.id[p]) for p in order}) < len(order):
            raise ValueError("two pieces share a score; merging order would depend on their place")
        #: When a piece comes into being: 0 for single characters, then by falling score.
        self.when = {p: 0 for p in words if len(p) == 1} | {p: k + 1 for k, p in enumerate(order)}
        self.parts: dict[str, tuple[str, str]] = {}
        for p in order:
            merged = self._merge(p, self.when[p])
            if len(merged) == 2:
                self.parts[p] = (merged[0], merged[1])
        self.known = {p for p in self.when if len(p) == 1} | set(self.parts)
        self.chars = {p for p in self.when if len(p) == 1}
        self.automaton = ahocorasick.Automaton()
        for p in self.known:
            self.automaton.add_word(p, p)
        self.automaton.make_automaton()
        self.pairs: dict[tuple[str, str], bool] = {}

    def _merge(self, text: str, before: int) -> list[str]:
        """Plain pair merging of a short text with pieces made earlier than `before`."""
        seq = list(text)
        while len(seq) > 1:
            best, at = before, -1
            for i in range(len(seq) - 1):
                made = self.when.get(seq[i] + seq[i + 1])
                if made is not None and made < best:
                    best, at = made, i
            if at < 0:
                break
            seq[at : at + 2] = [seq[at] + seq[at + 1]]
        return seq

    def compatible(self, a: str, b: str) -> bool:
        """True if the text a + b is encoded as exactly a, b.

        Undo the two pieces step by step, latest-made first, and look at the two fragments that touch: had they been
        able to merge before the later of them was consumed by its own next merge, the border would have vanished.
        """
        known = self.pairs.get((a, b))
        if known is None:
            if len(self.pairs) > 2_000_000:
                self.pairs.clear()
            known = self.pairs[a, b] = self._stays(a, b)
        return known

    def _stays(self, a: str, b: str) -> bool:
        when, parts = self.when, self.parts
        left, right = a, b
        # Time at which the touching fragment is swallowed by a larger one of its own piece; never for a whole piece.
        left_gone = right_gone = len(when) + 1
        while True:
            made = when.get(left + right)
            if made is not None and (made < left_gone and made < right_gone or made == right_gone and made < left_gone):
                return False
            # Step back in time past the later birth of the two.
            if when[left] >= when[right] and left in parts:
                left_gone, left = when[left], parts[left][1]
            elif right in parts:
                right_gone, right = when[right], parts[right][0]
            elif left in parts:
                left_gone, left = when[left], parts[left][1]
            else:
                return True

    def split(self, text: str) -> list[str]:
        """Pieces of a text of known characters that has a space mark at its start at most."""
        last: list[str | None] = [None] * len(text)
        compatible = self.compatible
        pairs = self.pairs
        for end, p in self.automaton.iter(text):
            # Exactly one piece passes at each place.
            if last[end] is None:
                start = end + 1 - len(p)
                if start == 0:
                    last[end] = p
                elif (before := last[start - 1]) is not None:
                    stays = pairs.get((before, p))
                    if compatible(before, p) if stays is None else stays:
                        last[end] = p
        out, at = [], len(text) - 1
        while at >= 0:
            p = last[at]
            out.append(p)
            at -= len(p)
        return out[::-1]

    def _spaces(self, n: int) -> list[int]:
        """A run of n space marks.  All pieces of marks alone share a score, so the leftmost pair that has a piece merges
        first: a stack of finished sizes, whose top grows by marks from the right or falls into the one below.
        """
        done: list[int] = []
        for _ in range(n):
            done.append(1)
            while len(done) > 1 and done[-2] + done[-1] in self.runs:
                done[-2:] = [done[-2] + done[-1]]
        return [self.id[SPACE_MARK * size] for size in done]

    def chunk_ids(self, chunk: str) -> list[int]:
        """Ids of one chunk: space marks, then characters that are none."""
        body = chunk.lstrip(SPACE_MARK)
        marks = len(chunk) - len(body)
        rest = SPACE_MARK * min(marks, 1) + body
        if marks < 2 and self.chars.issuperset(rest):
            return [self.id[p] for p in self.split(rest)]
        ids: list[int] = []
        at, n = 0, len(rest)
        while at < n:
            stop = at
            while stop < n and rest[stop] in self.chars:
                stop += 1
            if stop > at:
                ids += [self.id[p] for p in self.split(rest[at:stop])]
            if stop < n:
                ids += [self.byte[x] for x in rest[stop].encode()]
                stop += 1
            at = stop
        if marks > 1:
            alone = ids[:1] == [self.id[SPACE_MARK]]
            ids = self._spaces(marks if alone else marks - 1) + (ids[1:] if alone else ids)
        return ids

    def text_of(self, ids: list[int]) -> str:
        """Text of ids before the leading space is taken off; runs of byte ids are read as UTF-8."""
        back = self.byte_of
        if back.keys().isdisjoint(ids):
            return "".join([self.piece[i] for i in ids]).replace(SPACE_MARK, " ")
        out = bytearray()
        for i in ids:
            x = back.get(i)
            out += self.piece[i].encode() if x is None else bytes([x])
        return out.decode("utf-8", "replace").replace(SPACE_MARK, " ")


class Chunks(dict):
    """Chunk -> (decimal ids joined by commas, number of ids, decoded text), filled as chunks are asked for.

    Two generations bound its size: renew() makes the entries so far the old generation once there are CACHE of them,
    and an old entry that is asked for again moves on.
    """

    def __init__(self, merges: Merges) -> None:
        super().__init__()
        self.merges = merges
        self.old: dict[str, tuple[str, int, str]] = {}

    def __missing__(self, chunk: str) -> tuple[str, int, str]:
        got = self.old.get(chunk)
        if got is None:
            ids = self.merges.chunk_ids(chunk.replace(" ", SPACE_MARK))
            got = (",".join(map(str, ids)), len(ids), self.merges.text_of(ids))
        if len(chunk) <= LONGEST_KEPT:
            self[chunk] = got
        return got

    def renew(self) -> None:
        if len(self) >= CACHE:
            self.old = dict(self)
            self.clear()


class Codec:
    """Encodes and decodes whole texts chunk by chunk."""

    def __init__(self, path: str) -> None:
        self.merges = Merges(path)
        self.chunks = Chunks(self.merges)
        x = "".join(re.escape(c) for c in "\n\t\r" if c not in self.merges.chars)
        self.cut = re.compile(f"[ {SPACE_MARK}]+[^ {SPACE_MARK}{x}]*|[^ {SPACE_MARK}{x}]+" + (f"|[{x}]" if x else "")).findall

    def check(self, path: str) -> Codec:
        """Refuses a model whose normaliser is another than the one this codec follows."""
        model = sentencepiece.SentencePieceProcessor(model_file=path)
        for text in PROBES:
            ids = model.encode(text)
            if self.encode(text) != ids or self.decode(ids) != model.decode(ids):
                raise ValueError(f"the model normalises texts in a way that is not followed here: {text!r}")
        return self

    def run(self, text: str) -> tuple[tuple[str, ...], int, str]:
        """Per chunk the decimal ids joined by commas; number of ids; decoded text."""
        if not text:
            return (), 0, ""
        ids, n, texts = zip(*map(self.chunks.__getitem__, self.cut(" " + text)), strict=True)
        self.chunks.renew()
        out = "".join(texts)
        return ids, sum(n), out[1:] if out.startswith(" ") else out

    def encode(self, text: str | None) -> list[int]:
        return [int(x) for part in self.run(text or "")[0] for x in part.split(",")]

    def decode(self, ids: list[int]) -> str:
        out = self.merges.text_of(ids)
        return out[1:] if out.startswith(" ") else out


@held_by(__name__)
@lru_cache(maxsize=4)
def codec(path: str) -> Codec:
    return Codec(path).check(path)


def encode(docs: DataFrame, model_path: str, text_col: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """keep columns, ids array<int>, decoded string.

    A null or empty text has no ids and the empty decoded text.  Only the named columns are read, so extra columns with
    any name do no harm; repeated rows give repeated results; an empty table gives none.
    """
    names = list(keep)

    def run(it):
        c = codec(model_path)
        for b in batches(it):
            ids, back = [], []
            for t in b.column(len(names)).to_pylist():
                row = c.encode(t)
                ids.append(row)
                back.append(c.decode(row))
            yield pa.RecordBatch.from_arrays([*b.columns[: len(names)], pa.array(ids, pa.list_(pa.int32())), pa.array(back, pa.string())], [*names, "ids", "decoded"])

    src = docs.select(*names, docs[text_col].cast("string").alias("__text"))
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in src.schema.fields[:-1])
    return arrow_map(src, run, f"{kinds}, ids array<int>, decoded string")


def digests(docs: DataFrame, model_path: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every whole text; the digest form of encode().

    Null is empty; rows that repeat are answered each time, extra columns are dropped, an empty table gives none.
    """

    def run(it):
        c = codec(model_path)
        for b in batches(it):
            n, ids, back = [], [], []
            for t in b.column(1).to_pylist():
                parts, count, text = c.run(t or "")
                n.append(count)
                ids.append(hashlib.sha256(",".join(parts).encode()).hexdigest())
                back.append(hashlib.sha256(text.encode()).hexdigest())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(ids), pa.array(back)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return arrow_map(documents_of(docs), run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op3_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return digests(table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))
