"""Line dedup by equality, and by a segment-partition edit join.

Lines of any length that are equal are copies; a line is told apart by 128 bits of BLAKE2.  Two lines are near copies if
their edit distance in code points is `edits` or less and both have `shortest` code points or more: the method needs
segments long enough to tell lines apart.  Such a pair shares one of edits + 1 segments: the shorter line's segments are
indexed by (length, number, text), and the longer line probes that index with the substrings that could match, at the few
starts that the length difference allows.  Keys are hashes, made for all lines of a batch from prefix sums without
cutting a string.  The candidates that a parity sketch of neighbouring signs does not rule out are verified with banded
bit-parallel edit distance, many pairs side by side.

Plan: texts are parsed once, into rows of (line, place, sketch, keys); a task makes the keys of a line that repeats once.
Index and probes meet in an equi join on the key.  A segment that very many lines share is found in a sample of the
lines, and its members meet in a second join instead, by that segment and one of the parts of their sketch: of lines
within the distance one part at least is equal, so no pair is lost, and members that differ elsewhere never meet.  Classes
are connected components of the links.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import materialize, scoped
from .common import SPACE, U64, arrow_map, batches, documents_of, join_texts, mix, prefix_hash, slice_hash, table, unused
from .components import components

EDITS = 2
SHORTEST = 30
#: Longs of a sketch.
WIDE = 4
#: A segment with about so many lines or more, judged by the lines whose hash is divisible by SAMPLE, is a hot one.
HOT, SAMPLE = 4096, 64
#: Lines that a task remembers, so as to make their keys once.
REMEMBERED = 200_000


def segments(length: np.ndarray, edits: int) -> tuple[np.ndarray, np.ndarray]:
    """(start, size) of the edits + 1 segments of lines of the given lengths, sizes even but for one."""
    parts = edits + 1
    small, longer = length // parts, length % parts
    i = np.arange(parts)
    size = small[:, None] + (i >= parts - longer[:, None])
    return np.cumsum(size, axis=1) - size, size


def _windows(i: int, differ: int, edits: int) -> range:
    """Starts, relative to the segment's own, at which segment i of a line shorter by `differ` can stand.

    Edits left of the first matching segment are fewer than its number, edits right of it fewer than what remains, and
    the two sides together make up the difference of the lengths.
    """
    before, after = i, edits - i
    return range(max(-before, differ - after), min(before, differ + after) + 1)


class Lines:
    """All lines of a batch of texts as code points, with one hash each."""

    def __init__(self, texts: list[str | None]) -> None:
        joined = "\n".join("" if t is None else t for t in texts) + "\n" if texts else ""
        self.code = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
        self.prefix = prefix_hash(self.code.astype(U64) + U64(1))
        self.stop = np.flatnonzero(self.code == 10)
        self.start = np.concatenate([[0], self.stop[:-1] + 1]) if len(self.stop) else self.stop
        per = np.array([1 + (t or "").count("\n") for t in texts], np.int64)
        self.owner = np.repeat(np.arange(len(texts)), per)
        self.number = np.arange(len(self.owner)) - np.repeat(np.cumsum(per) - per, per)
        self.length = self.stop - self.start
        self.text = joined[:-1].split("\n") if texts else []

    def identity(self, pick: np.ndarray) -> np.ndarray:
        """(line x 2) 64 bits each."""
        raw = b"".join([hashlib.blake2b(self.text[i].encode("utf-8", "surrogatepass"), digest_size=16).digest() for i in pick.tolist()])
        return np.frombuffer(raw, "<i8").reshape(-1, 2)

    def spoken(self) -> np.ndarray:
        """Whether each line holds a word."""
        sign = (self.code > 255) | ~SPACE[np.minimum(self.code, 255)]
        seen = np.concatenate([[0], np.cumsum(sign)])
        return seen[self.stop] > seen[self.start]

    def sketch(self, pick: np.ndarray) -> np.ndarray:
        """(line x WIDE) parities of neighbouring sign pairs; one edit flips four bits at most."""
        code = self.code.astype(U64)
        with np.errstate(over="ignore"):
            bit = mix(code[:-1] * U64(0x9E3779B97F4A7C15) + code[1:] * U64(0xC2B2AE3D27D4EB4F))
        one, word = U64(1) << (bit & U64(63)), (bit >> U64(6)) & U64(WIDE - 1)
        first, last = self.start[pick], np.maximum(self.stop[pick] - 1, self.start[pick])
        out = np.empty((len(pick), WIDE), np.int64)
        for k in range(WIDE):
            flips = np.concatenate([np.zeros(1, U64), np.bitwise_xor.accumulate(np.where(word == U64(k), one, U64(0)))])
            out[:, k] = (flips[last] ^ flips[first]).view(np.int64)
        return out

    def keys(self, pick: np.ndarray, edits: int) -> np.ndarray:
        """Keys per picked line: first the edits + 1 of the index, then the probes.

        Probes of a line for lines of its own length at its own segments are its index keys; they are not repeated.
        """
        start, length = self.start[pick], self.length[pick]
        index, probe = [], []
        for differ in range(edits + 1):
            other = length - differ
            at, size = segments(other, edits)
            for i in range(edits + 1):
                for shift in _windows(i, differ, edits):
                    s = start + at[:, i] + shift
                    inside = (at[:, i] + shift >= 0) & (at[:, i] + shift + size[:, i] <= length)
                    s0 = np.where(inside, s, start)
                    with np.errstate(over="ignore"):
                        key = mix(slice_hash(self.prefix, s0, s0 + size[:, i]) + other.astype(U64) * U64(0x9E3779B97F4A7C15) + U64(i + 1) * U64(0xD6E8FEB86659FD93))
                    if differ == 0 and shift == 0:
                        index.append(key)
                    else:
                        # A start outside the line gets a key of its place alone, at best no candidate.
                        probe.append(np.where(inside, key, mix(key + s.astype(U64))))
        return np.stack(index + probe, axis=1)


ROWS = "h1 long, h2 long, doc_id long, line_no int, sketch array<long>, keys array<long>"


def line_rows(docs: DataFrame, edits: int, shortest: int, all_lengths: bool) -> DataFrame:
    """(h1, h2, doc_id, line_no, sketch, keys) of all lines with a word, or of those with `shortest` signs or more.

    sketch and keys are null for shorter lines and for those that the task has met before.
    """

    def run(it):
        seen: set[bytes] = set()
        for b in batches(it, 1 << 20):
            x = Lines(b.column(1).to_pylist())
            pick = np.flatnonzero(x.spoken() if all_lengths else x.length >= shortest)
            ids = np.array([-1 if v is None else v for v in b.column(0).to_pylist()], np.int64)
            name = x.identity(pick)
            first = np.zeros(len(pick), bool)
            raw = name.tobytes()
            for i in np.flatnonzero(x.length[pick] >= shortest).tolist():
                h = raw[16 * i : 16 * i + 16]
                if h not in seen:
                    seen.add(h)
                    first[i] = True
            if len(seen) > REMEMBERED:
                seen.clear()
            keyed = pick[first]
            cols = [pa.array(name[:, 0].copy()), pa.array(name[:, 1].copy()), pa.array(ids[x.owner[pick]]), pa.array(x.number[pick].astype(np.int32))]
            cols += [_nested(v, first) for v in (x.sketch(keyed), x.keys(keyed, edits).view(np.int64))]
            yield pa.RecordBatch.from_arrays(cols, ["h1", "h2", "doc_id", "line_no", "sketch", "keys"])

    return arrow_map(docs.filter("doc_id IS NOT NULL"), run, ROWS)


def _nested(values: np.ndarray, there: np.ndarray) -> pa.Array:
    """Lists of equal length where `there`, null elsewhere."""
    offsets = np.concatenate([[0], np.cumsum(there)]).astype(np.int32) * values.shape[1]
    return pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.ascontiguousarray(values).ravel()), mask=pa.array(~there))


#: Signs, padding included, that are compared side by side; a longer pair goes alone.
CELLS = 1 << 20


def within(a: list[np.ndarray], b: list[np.ndarray], edits: int) -> np.ndarray:
    """True where the edit distance of a[k] and b[k] is `edits` or less.

    Pairs of similar length are compared side by side, as many as CELLS signs hold.
    """
    size = np.array([len(x) + len(y) + 2 * edits + 4 for x, y in zip(a, b, strict=True)], np.int64)
    out, group = np.zeros(len(a), bool), []
    for k in np.argsort(size, kind="stable").tolist():
        if group and (len(group) + 1) * int(size[k]) > CELLS:
            out[group] = _side_by_side([a[i] for i in group], [b[i] for i in group], edits)
            group = []
        group.append(k)
    if group:
        out[group] = _side_by_side([a[i] for i in group], [b[i] for i in group], edits)
    return out


def _side_by_side(a: list[np.ndarray], b: list[np.ndarray], edits: int) -> np.ndarray:
    """within() for pairs that advance together.

    Banded bit-parallel: column j of the table is kept for rows j - edits .. j + edits only, as vertical differences in
    the bits of one word per pair, bit 0 for the lowest row number.
    """
    n = len(a)
    band = 2 * edits + 1
    if band > 62:
        raise ValueError("the band must fit into one word")
    la, lb = np.array([len(x) for x in a], np.int64), np.array([len(x) for x in b], np.int64)
    out = np.abs(la - lb) <= edits
    if n == 0:
        return out
    # Rows are signs of a (padded on both sides), columns signs of b; paddings never match.
    rows = np.full((n, int(la.max()) + int(lb.max()) + band + 2), 0xFFFFFFFF, np.uint32)
    cols = np.full((n, int(lb.max()) + 1), 0xFFFFFFFE, np.uint32)
    for k in range(n):
        rows[k, edits : edits + la[k]] = a[k]
        cols[k, : lb[k]] = b[k]
    one, full = U64(1), U64((1 << band) - 1)
    # Before the first column: rows -edits .. edits; vertical differences are -1 above row 0 (so that the padding cannot
    # help) and +1 from row 1 on. The cell followed is row j + edits, whose value starts at edits.
    plus, minus = np.full(n, ((1 << band) - 1) & ~((1 << (edits + 1)) - 1), U64), np.zeros(n, U64)
    low = np.full(n, edits, np.int64)
    score = low.copy()
    final = np.full(n, edits + 1, np.int64)
    bits = U64(1) << np.arange(band, dtype=U64)
    for j in range(int(lb.max()) + 1):
        # Value at row la, column j: walk from the followed lowest row up to row la by vertical differences.
        done = np.flatnonzero((lb == j) & out)
        if len(done):
            value = score[done].copy()
            for r in range(band - 1, 0, -1):
                step = (la[done] < j - edits + r).astype(np.int64)
                up = ((plus[done] >> U64(r)) & one).astype(np.int64) - ((minus[done] >> U64(r)) & one).astype(np.int64)
                value -= step * up
            final[done] = value
        if j == int(lb.max()):
            break
        # The band moves one row down with each column: row j + 1 - edits .. j + 1 + edits of column j + 1.
        eq = ((rows[:, j : j + band] == cols[:, j : j + 1]) * bits).sum(axis=1, dtype=U64)
        p, m = plus >> one, minus >> one
        with np.errstate(over="ignore"):
            d0 = ((((eq & p) + p) ^ p) | eq | m) & full
        hp = (m | (~(d0 | p) & full)) & full
        hn = p & d0
        # On the diagonal the followed cell grows by one unless its diagonal difference is 0.
        score += 1 - ((d0 >> U64(band - 1)) & one).astype(np.int64)
        # Vertical differences of the new column come from horizontal differences one row above.
        hp_up, hn_up = ((hp << one) | one) & full, (hn << one) & full
        plus, minus = (hn_up | (~(d0 | hp_up) & full)) & full, hp_up & d0
    return out & (final <= edits)


@scoped
def similar_lines(docs: DataFrame, edits: int = EDITS, shortest: int = SHORTEST) -> DataFrame:
    """doc_id, line_no, class_doc, class_line, n_links of every line of `shortest` signs or more.

    Lines are what `\\n` separates, numbered from 0.  A class holds equal lines and lines that links reach; its name is
    its first occurrence by (doc_id, line_no).  n_links counts the other texts within the distance.  Null text: empty.
    Rows without doc_id take no part; rows that repeat repeat the result; extra columns are dropped; an empty table gives
    no rows.
    """
    return _classes(docs, edits, shortest, False)


@scoped
def line_classes(docs: DataFrame, edits: int = EDITS, shortest: int = SHORTEST) -> DataFrame:
    """similar_lines() of every line with a word, whatever its length.

    Lines under `shortest` signs are in a class with their equals alone, without links; lines without a word have no row.
    """
    return _classes(docs, edits, shortest, True)


def _candidates(rows: DataFrame, edits: int) -> DataFrame:
    """(a, b), a < b: lines (h1) that share a segment and whose sketches allow the distance."""
    parts = edits + 1
    keyed = rows.filter("keys IS NOT NULL")
    hot = keyed.filter(F.col("h1") % SAMPLE == 0).select(F.explode("keys").alias("key")).groupBy("key").count()
    # Written, so that its size is known: Spark broadcasts it only below its own limit of bytes.
    hot = materialize(hot.filter(F.col("count") >= HOT // SAMPLE).select("key"), "hot")
    fold = F.col("sketch")[0].bitwiseXOR(F.col("sketch")[1]).bitwiseXOR(F.col("sketch")[2]).bitwiseXOR(F.col("sketch")[3])
    near = F.bit_count(F.col("sa").bitwiseXOR(F.col("sb"))) <= 4 * edits

    def side(keys: Column, line: str, sketch: str) -> DataFrame:
        exploded = keyed.select(F.explode(keys).alias("key"), F.col("h1").alias(line), fold.alias(sketch)).join(hot, "key", "left_anti")
        # Tasks may have made the keys of one line more than once.
        return exploded.repartition("key").dropDuplicates(["key", line])

    index = side(F.slice("keys", 1, parts), "a", "sa")
    probes = side(F.slice("keys", parts + 1, F.size("keys")), "b", "sb")
    same = index.select("key", F.col("a").alias("b"), F.col("sa").alias("sb"))
    found = index.join(probes, "key").filter(near & (F.col("a") != F.col("b")))
    level = index.join(same, "key").filter(near & (F.col("a") < F.col("b")))
    pairs = found.select("a", "b").unionByName(level.select("a", "b"))
    if hot.limit(1).count():
        pairs = pairs.unionByName(_hot_candidates(keyed, hot, edits))
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _hot_candidates(keyed: DataFrame, hot: DataFrame, edits: int) -> DataFrame:
    """(a, b): members of hot segments that also share a part of the sketch.

    The sketches of a pair within the distance differ in 4 * edits bits at most, so one of 4 * edits + 1 parts is equal.
    """
    n = 4 * edits + 1
    size = min(64 * WIDE // n, 63)

    def part(j: int) -> Column:
        word, shift = divmod(j * size, 64)
        low = F.shiftrightunsigned(F.col("sketch")[word], shift)
        if shift + size > 64:
            low = low.bitwiseOR(F.shiftleft(F.col("sketch")[word + 1], 64 - shift))
        return low.bitwiseAND(F.lit((1 << size) - 1))

    members = keyed.select(F.posexplode("keys").alias("pos", "key"), "h1", "sketch").join(hot, "key")
    members = members.select("key", (F.col("pos") <= edits).alias("indexed"), "h1", "sketch", F.posexplode(F.array(*[part(j) for j in range(n)])).alias("j", "bits"))
    rows = materialize(members.dropDuplicates(["key", "j", "bits", "h1", "indexed"]), "members")
    a = rows.filter("indexed").select("key", "j", "bits", F.col("h1").alias("a"), F.col("sketch").alias("sa"))
    b = rows.select("key", "j", "bits", F.col("h1").alias("b"), F.col("sketch").alias("sb"), "indexed")
    differ = sum((F.bit_count(F.col("sa")[i].bitwiseXOR(F.col("sb")[i])) for i in range(WIDE)), F.lit(0))
    return a.join(b, ["key", "j", "bits"]).filter((differ <= 4 * edits) & F.when(F.col("indexed"), F.col("a") < F.col("b")).otherwise(F.col("a") != F.col("b"))).select("a", "b")


def _classes(docs: DataFrame, edits: int, shortest: int, all_lengths: bool) -> DataFrame:
    docs = documents_of(docs)
    rows = materialize(line_rows(docs, edits, shortest, all_lengths), "lines")
    pairs = materialize(_candidates(rows, edits), "candidates")
    first = materialize(rows.groupBy("h1", "h2").agg(F.min(F.struct("doc_id", "line_no")).alias("at")), "firsts")
    links = materialize(_verify(pairs, first, docs, edits), "links")
    label = components(links)
    degree = links.select(F.explode(F.array("a", "b")).alias("at")).groupBy("at").agg(F.count("*").alias("n_links"))
    named = first.join(label.withColumnRenamed("node", "at"), "at", "left").join(degree, "at", "left")
    named = named.select("h1", "h2", F.coalesce("component", "at").alias("class"), F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"))
    named = materialize(named, "named")
    out = rows.select("h1", "h2", "doc_id", "line_no").join(named, ["h1", "h2"])
    return out.select("doc_id", "line_no", F.col("class.doc_id").alias("class_doc"), F.col("class.line_no").alias("class_line"), "n_links")


def _verify(pairs: DataFrame, first: DataFrame, docs: DataFrame, edits: int) -> DataFrame:
    """Links (a, b), each a first occurrence (doc_id, line_no): candidate pairs whose texts are near enough."""
    wanted = first.join(pairs.select(F.explode(F.array("a", "b")).alias("h1")).distinct(), "h1", "left_semi")
    asked = materialize(wanted.groupBy("at.doc_id").agg(F.collect_list(F.struct("at.line_no", "h1", "h2")).alias("want")), "asked")

    def cut(it):
        # Rows may share a doc_id: a line is the asked one only if its identity is.
        for batch in it:
            for b in batches([batch], 1 << 20):
                x = Lines(b.column(1).to_pylist())
                begin = np.searchsorted(x.owner, np.arange(b.num_rows + 1))
                found = [(begin[i] + w["line_no"], w["h1"], w["h2"], w["line_no"], i) for i, ws in enumerate(b.column(2).to_pylist()) for w in ws if begin[i] + w["line_no"] < begin[i + 1]]
                at = np.array([f[0] for f in found], np.int64)
                name = x.identity(at)
                ids = b.column(0).to_pylist()
                out = [(h1, ids[i], no, x.text[k]) for (k, h1, h2, no, i), n in zip(found, name.tolist(), strict=True) if n == [h1, h2]]
                cols = list(zip(*out, strict=True)) if out else [[]] * 4
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int32(), pa.string()), strict=True)], ["h1", "doc_id", "line_no", "text"])

    text = arrow_map(join_texts(docs, asked, "want").select("doc_id", "text", "want"), cut, "h1 long, doc_id long, line_no int, text string")
    text = materialize(text.select("h1", F.struct("doc_id", "line_no").alias("at"), "text").dropDuplicates(["h1", "at"]), "texts")
    side = lambda c: text.select(F.col("h1").alias(c), F.col("at").alias(f"at_{c}"), F.col("text").alias(f"t_{c}"))
    joined = pairs.join(side("a"), "a").join(side("b"), "b").select("at_a", "at_b", "t_a", "t_b")

    def run(it):
        for batch in it:
            for b in batches([batch], 1 << 20):
                code = [[np.frombuffer((t or "").encode("utf-32-le", "surrogatepass"), np.uint32) for t in b.column(k).to_pylist()] for k in (2, 3)]
                kept = b.select([0, 1]).filter(pa.array(within(code[0], code[1], edits)))
                yield pa.RecordBatch.from_arrays(kept.columns, ["a", "b"])

    at = "struct<doc_id:bigint,line_no:int>"
    return arrow_map(joined, run, f"a {at}, b {at}").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def drop_lines(docs: DataFrame, classes: DataFrame) -> DataFrame:
    """docs without the lines that are not the first of their class; n_chars is set anew, other columns stay.

    A document of which no line with a sign other than white space is left is dropped; one that had none from the start,
    or no text or no doc_id, is kept as it is.  Rows that repeat a doc_id all lose the lines of those numbers.  An empty
    table gives none.
    """
    names = docs.columns
    key, drop = unused(names, "__id"), unused(names, "__drop")
    doomed = classes.filter((F.col("doc_id") != F.col("class_doc")) | (F.col("line_no") != F.col("class_line"))).groupBy(F.col("doc_id").alias(key)).agg(F.collect_set("line_no").alias(drop))
    # The same way at every size: what is dropped grows with the documents.
    src = docs.join(materialize(doomed, "doomed").hint("shuffle_hash"), docs["doc_id"] == F.col(key), "left").drop(key)

    def run(it):
        for batch in it:
            for b in batches([batch], 1 << 20):
                texts, out, keep = b.column(b.schema.get_field_index("text")).to_pylist(), [], []
                drops = b.column(b.num_columns - 1).to_pylist()
                for t, drop in zip(texts, drops, strict=True):
                    if drop and t is not None:
                        gone = set(drop)
                        t = "\n".join([x for i, x in enumerate(t.split("\n")) if i not in gone])
                    out.append(t)
                    keep.append(not drop or bool(t and t.strip(" \t\n\x0b\x0c\r")))
                cols = {n: b.column(n) for n in names}
                cols["text"] = pa.array(out, pa.string())
                if "n_chars" in cols:
                    cols["n_chars"] = pa.array([n if not d else len(t or "") for n, d, t in zip(cols["n_chars"].to_pylist(), drops, out, strict=True)], cols["n_chars"].type)
                yield pa.RecordBatch.from_arrays([cols[n] for n in names], names).filter(pa.array(keep, pa.bool_()))

    return arrow_map(src, run, docs.schema.simpleString().removeprefix("struct<").removesuffix(">"))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_classes(table(spark, sf_dir, "documents"))
