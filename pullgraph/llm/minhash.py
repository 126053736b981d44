"""MinHash near-duplicates with odd sketches.

Every text's set of word shingles gives BANDS * ROWS MinHash samples.  Bands of samples make bucket keys; the samples
are also folded into an odd sketch, a bitmap in which each (place, sample) flips one bit, so that the XOR of two sketches
holds only what differs and its population count tells high similarities apart.  A pair is looked at if it shares a
bucket, its set sizes allow the threshold and its sketches are near enough; it is linked only after the full sets
were compared.

No pair is left out, and no bucket is expanded into all its pairs:
1. texts with equal sets are one class, with its smallest doc_id standing for it;
2. in each bucket all members are compared with one of them (twice, with another one), which joins most;
3. members that then are in no component with the bucket's chosen member are compared with all members of other
   components.  Two members of one component need no comparison, whatever their similarity.  This is done inside the
   task, a block of members against a stream of those apart, in the first bucket that a pair shares, and only links come
   out; buckets of more than BLOCK members are dealt out to several tasks.
Bands have as many rows as keep the chance that a pair at the threshold t shares no bucket, (1 - t**rows)**bands, at MISS or
less (32 bands of 4 rows and 5e-8 at 0.8), and sketches rule a pair out only beyond DEVIATIONS standard deviations from
what the threshold makes likely.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import materialize, release, scoped
from .common import Runs, U64, Words, arrow_map, batches, documents_of, mix, table
from .components import components

SAMPLES = 128
SKETCH_BITS = 512
THRESHOLD = 80
#: Largest chance that a pair at the threshold shares no bucket; standard deviations left to the sketches.
MISS, DEVIATIONS = 1e-7, 6
#: Members of a bucket that one task holds at a time in the last comparison.
BLOCK = 512

SIGNATURES = "doc_id long, version long, n_shingles long, set_id binary, bands array<long>, sketch array<long>"


def rows_per_band(threshold: int) -> int:
    """Most samples a band may have; with one, a pair below about 12 % similarity could still be missed."""
    t = threshold / 100
    return next((r for r in (16, 8, 4, 2) if (1 - t**r) ** (SAMPLES // r) <= MISS), 1)


def slack(threshold: int) -> int:
    """Differing bits up to which a pair goes to the exact comparison.

    Of SAMPLES places k differ, binomially, and each flips one bit in either sketch, so 2 k flips fall on SKETCH_BITS bits;
    variance has one part from the number of places and one from flips that fall together.
    """
    t, n = threshold / 100, SKETCH_BITS
    k = SAMPLES * (1 - t)
    odd = lambda flips: n / 2 * (1 - (1 - 2 / n) ** flips)
    share = odd(2 * k) / n
    spread = (odd(2 * (k + 1)) - odd(2 * k)) ** 2 * SAMPLES * t * (1 - t) + n * share * (1 - share)
    return min(n, math.ceil(odd(2 * k) + DEVIATIONS * math.sqrt(spread)))


def shingle_sets(texts: list[str | None], width: int) -> list[np.ndarray]:
    """Sorted distinct shingle identities of each text; fewer words than width: the whole sequence as one; none: empty."""
    w = Words(texts, lower_ascii=True)
    runs = Runs(w.hash ^ mix(w.hash2))
    every = runs.of(np.arange(max(len(w.start) - width + 1, 0)), width)
    out = []
    for first, n in zip(w.first[:-1].tolist(), w.n.tolist(), strict=True):
        if n == 0:
            out.append(np.zeros(0, U64))
        elif n < width:
            out.append(runs.of(np.array([first]), n))
        else:
            out.append(np.unique(every[first : first + n - width + 1]))
    return out


def exact_sets(texts: list[str | None], width: int) -> list[np.ndarray]:
    """Sets as shingle_sets(), of numbers that are equal within the call if and only if the words are, by their bytes."""
    w = Words(texts, lower_ascii=True)
    base = int(w.number.max(initial=0)) + 1
    every = w.number
    for k in range(1, width):
        # Numbers of runs of k words, made dense, times those of the next word: below 2**63 for any batch.
        dense = every if k == 1 else np.unique(every, return_inverse=True)[1].reshape(-1)
        every = dense[: max(len(dense) - 1, 0)] * base + w.number[k:]
    out = []
    for first, n in zip(w.first[:-1].tolist(), w.n.tolist(), strict=True):
        if n < width:
            # Too short a text is one shingle, equal to one of the same words alone: below 0, by length and words.
            out.append(np.array([-1 - hash(tuple(w.number[first : first + n].tolist())) % (1 << 62)]) if n else np.zeros(0, np.int64))
        else:
            out.append(np.unique(every[first : first + n - width + 1]))
    return out


def similar(a: np.ndarray, b: np.ndarray, threshold: int) -> bool:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= threshold * (len(a) + len(b) - both)


class Signer:
    def __init__(self, threshold: int = THRESHOLD, bits: int = SKETCH_BITS, seed: int = 11) -> None:
        self.rows, self.bits = rows_per_band(threshold), bits
        self.bands = bands = SAMPLES // self.rows
        rows = self.rows
        self.factor = np.random.default_rng(seed).integers(0, 2**63, bands * rows, dtype=np.uint64) * U64(2) + U64(1)
        self.place = mix(np.arange(1, bands * rows + 1, dtype=U64))

    def samples(self, s: np.ndarray) -> np.ndarray:
        low = np.full(len(self.factor), np.iinfo(np.uint64).max, U64)
        with np.errstate(over="ignore"):
            for at in range(0, len(s), 2048):
                np.minimum(low, np.multiply.outer(s[at : at + 2048], self.factor).min(axis=0), out=low)
        return low

    def keys(self, samples: np.ndarray) -> np.ndarray:
        """Bucket keys (text x band), different for different bands."""
        with np.errstate(over="ignore"):
            x = mix(samples * self.place)
            return mix(x.reshape(len(samples), self.bands, self.rows).sum(axis=2, dtype=U64))

    def sketches(self, samples: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            bit = (mix(samples + self.place) % U64(self.bits)).astype(np.int64)
        flips = np.bincount((bit + np.arange(len(samples))[:, None] * self.bits).ravel(), minlength=len(samples) * self.bits)
        return np.packbits((flips & 1).astype(np.uint8).reshape(len(samples), self.bits), axis=1).view(np.int64)


def signatures(docs: DataFrame, width: int, threshold: int = THRESHOLD) -> DataFrame:
    """One row per row: version of the text, set size, set identity, bucket keys and odd sketch."""

    def run(it):
        signer = Signer(threshold)
        names = ["doc_id", "version", "n_shingles", "set_id", "bands", "sketch"]
        for b in batches(it, 1 << 20):
            sets = shingle_sets(b.column(1).to_pylist(), width)
            samples = np.stack([signer.samples(s) for s in sets])
            keys, sketches = signer.keys(samples).view(np.int64), signer.sketches(samples)
            yield pa.RecordBatch.from_arrays(
                [
                    b.column(0),
                    b.column(2),
                    pa.array([len(s) for s in sets], pa.int64()),
                    pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets], pa.binary()),
                    pa.array(list(keys), pa.list_(pa.int64())),
                    pa.array(list(sketches), pa.list_(pa.int64())),
                ],
                names,
            )

    return arrow_map(docs, run, SIGNATURES)


def _plausible(a: str, b: str, threshold: int) -> Column:
    """Sizes and sketches of rows a and b allow the threshold."""
    n, m = F.col(f"{a}.n_shingles"), F.col(f"{b}.n_shingles")
    differ = sum((F.bit_count(F.col(f"{a}.sketch")[i].bitwiseXOR(F.col(f"{b}.sketch")[i])) for i in range(SKETCH_BITS // 64)), F.lit(0))
    return (100 * F.least(n, m) >= threshold * F.greatest(n, m)) & (differ <= slack(threshold))


def _confirm(pairs: DataFrame, texts: DataFrame, width: int, threshold: int) -> DataFrame:
    """The pairs (a, b) with 100 * intersection >= threshold * union, on full sets."""

    def run(it):
        for batch in it:
            for b in batches([batch], 1 << 20):
                ids_a, ids_b = b.column(0).to_pylist(), b.column(1).to_pylist()
                head = [i for i, a in enumerate(ids_a) if i == 0 or a != ids_a[i - 1]]
                sets = exact_sets([b.column(2)[i].as_py() for i in head] + b.column(3).to_pylist(), width)
                own, keep = -1, []
                for i, a in enumerate(ids_a):
                    own += i == 0 or a != ids_a[i - 1]
                    if similar(sets[own], sets[len(head) + i], threshold):
                        keep.append(i)
                yield pa.RecordBatch.from_arrays([pa.array([ids_a[i] for i in keep], pa.int64()), pa.array([ids_b[i] for i in keep], pa.int64())], ["a", "b"])

    right = texts.select(F.col("doc_id").alias("b"), F.col("text").alias("text_b"))
    left = texts.select(F.col("doc_id").alias("a"), F.col("text").alias("text_a"))
    # Joined on a last, so that the rows of one a follow each other and its set is made once.
    joined = pairs.join(right, "b").join(left.hint("merge"), "a").select("a", "b", "text_a", "text_b")
    return arrow_map(joined, run, "a long, b long")


HELD = ["bucket", "salt", "side", "doc_id", "c", "main", "n_shingles", "sketch", "bands"]


def _matches(o: dict, m: dict, threshold: int) -> np.ndarray:
    """Places of block m that row o of a component apart has to be compared with, in this bucket."""
    ok = (m["c"] != o["c"]) & (m["main"] | (m["doc_id"] > o["doc_id"]))
    low, high = np.minimum(m["n_shingles"], o["n_shingles"]), np.maximum(m["n_shingles"], o["n_shingles"])
    at = np.flatnonzero(ok & (100 * low >= threshold * high))
    if len(at):
        at = at[np.bitwise_count(m["sketch"][at] ^ o["sketch"]).sum(axis=1) <= slack(threshold)]
    if len(at):
        # The first band two rows share is the one in which they are compared.
        at = at[(m["bands"][at] == o["bands"]).argmax(axis=1) == int((o["bands"] == o["bucket"]).argmax())]
    return at


def _blocks(it, extra: int = 0):
    """Streams (member block, rows apart) from rows sorted by bucket, salt, side: members first (side 0), one block per
    (bucket, salt), then slices of those apart.  A row is a position in the arrays of its slice."""
    now, members, more = None, None, []
    for batch in it:
        for b in batches([batch], 1 << 20):
            n = b.num_rows
            col = {c: b.column(i).to_numpy(zero_copy_only=False) for i, c in enumerate(HELD[:7])}
            for i, c in ((7, "sketch"), (8, "bands")):
                col[c] = b.column(i).flatten().to_numpy(zero_copy_only=False).reshape(n, -1)
            texts = b.column(9) if extra else None
            edge = np.flatnonzero((np.diff(col["bucket"]) != 0) | (np.diff(col["salt"]) != 0) | (np.diff(col["side"]) != 0)) + 1
            for x, y in zip([0, *edge], [*edge, n], strict=True):
                key = (col["bucket"][x], col["salt"][x])
                part = {c: v[x:y] for c, v in col.items()} | ({"text": texts.slice(x, y - x)} if extra else {})
                if key != now:
                    now, members, more = key, None, []
                if part["side"][0] == 0:
                    more.append(part)
                    members = None
                elif more:
                    if members is None:
                        members = {c: np.concatenate([p[c] for p in more]) for c in HELD} | ({"text": [t for p in more for t in p["text"].to_pylist()]} if extra else {})
                    yield members, part


def _row(part: dict, i: int) -> dict:
    return {c: part[c][i] for c in HELD}


def _participants(held: DataFrame, threshold: int) -> DataFrame:
    """The rows of held that have a comparison to make: at most one per row, however many pairs there are."""

    def run(it):
        for members, part in _blocks(it):
            hit = np.zeros(len(members["doc_id"]), bool)
            outside = []
            for i in range(len(part["doc_id"])):
                at = _matches(_row(part, i), members, threshold)
                if len(at):
                    hit[at] = True
                    outside.append(i)
            at = np.flatnonzero(hit)
            if len(at):
                rows = [np.concatenate([members[c][at], part[c][outside]]) for c in ("bucket", "salt", "side", "doc_id")]
                yield pa.RecordBatch.from_arrays([pa.array(r) for r in rows], ["bucket", "salt", "side", "doc_id"])

    return arrow_map(held, run, "bucket long, salt int, side int, doc_id long")


def _confirm_apart(held: DataFrame, width: int, threshold: int) -> DataFrame:
    """Links (a, b) between rows of different components; one link to a component is enough for a row."""

    def run(it):
        last, sets = None, []
        for members, part in _blocks(it, 1):
            if members is not last:
                last, sets = members, shingle_sets(members["text"], width)
            own = shingle_sets(part["text"].to_pylist(), width)
            out = []
            for i in range(len(own)):
                o, done = _row(part, i), set()
                for k in _matches(o, members, threshold):
                    if members["c"][k] in done:
                        continue
                    if similar(own[i], sets[k], threshold) and similar(*exact_sets([part["text"][i].as_py(), members["text"][k]], width), threshold):
                        done.add(members["c"][k])
                        x, y = int(o["doc_id"]), int(members["doc_id"][k])
                        out.append((min(x, y), max(x, y)))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["a", "b"])

    return arrow_map(held, run, "a long, b long")


def _links_apart(known: DataFrame, apart: DataFrame, reps: DataFrame, texts: DataFrame, width: int, threshold: int) -> DataFrame:
    """All links that are left: between members of a bucket that are in different components."""
    sizes = apart.select("bucket", F.ceil(F.col("n") / BLOCK).cast("int").alias("salts"))
    rows = known.join(sizes, "bucket").join(reps.select("doc_id", "n_shingles", "sketch", "bands"), "doc_id")
    main = known.filter("doc_id = p2").select("bucket", F.col("c").alias("m"))
    rows = materialize(rows.join(main, "bucket").withColumn("main", F.col("c") == F.col("m")), "apart")
    inside = rows.withColumn("salt", F.pmod(F.xxhash64("doc_id"), "salts").cast("int")).withColumn("side", F.lit(0))
    outside = rows.filter("NOT main").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).withColumn("side", F.lit(1))
    held = inside.select(*HELD).unionByName(outside.select(*HELD))
    parts = int(held.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = lambda df: df.repartition(parts, "bucket", "salt").sortWithinPartitions("bucket", "salt", "side")
    some = materialize(_participants(dealt(held), threshold).distinct(), "participants")
    again = held.join(some, ["bucket", "salt", "side", "doc_id"], "left_semi").join(texts, "doc_id").select(*HELD, "text")
    return _confirm_apart(dealt(again), width, threshold)


@scoped
def near_duplicates(docs: DataFrame, width: int = 2, threshold: int = THRESHOLD) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of every row.

    Links join texts with 100 * intersection >= threshold * union of their shingle sets; component_id is the smallest
    doc_id that links reach.  Null and empty texts and texts without words have an empty set and no link.  Rows that
    repeat an id and text repeat the result; of rows that share an id with different texts, the one whose text has the
    smallest hash stands for all in links, and n_shingles is each row's own.  A row without doc_id takes no part: its
    component_id is null, and it is kept.  Extra columns are dropped.  An empty table gives none.
    """
    docs = documents_of(docs, F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("version"))
    sigs = materialize(signatures(docs, width, threshold), "signatures")
    one = materialize(sigs.filter("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min(F.struct("version", "set_id", "n_shingles")).alias("m")).select("doc_id", "m.set_id", "m.n_shingles", "m.version"), "documents")
    # Written, so that the join has a shuffle of its own on either side, whose large partitions can be split.
    classes = materialize(one.filter("n_shingles > 0").groupBy("set_id").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n")), "classes")
    many = one.join(classes.filter("n > 1").select("set_id", "rep"), "set_id").select("doc_id", "rep")
    member = materialize(many, "membership")
    alone = classes.select(F.col("rep").alias("doc_id"))
    # Joined on doc_id alone, so that what is left of it needs no other shuffle.
    chosen = one.join(alone, "doc_id", "left_semi").select("doc_id", F.col("version").alias("own"))
    reps = sigs.join(chosen, "doc_id").filter("version = own").drop("own").dropDuplicates(["doc_id"])

    slots = materialize(reps.select("doc_id", F.explode("bands").alias("bucket")), "slots")
    shared = slots.groupBy("bucket").agg(F.min(F.struct(F.xxhash64("doc_id", F.lit(1)), "doc_id")).alias("p1"), F.min(F.struct(F.xxhash64("doc_id", F.lit(2)), "doc_id")).alias("p2"), F.count("*").alias("n")).filter("n > 1")
    # Written, so that the join has a shuffle of its own on either side, whose large partitions can be split.
    shared = materialize(shared, "shared")
    crowd = materialize(slots.join(shared.select("bucket", F.col("p1.doc_id").alias("p1"), F.col("p2.doc_id").alias("p2")), "bucket"), "crowd")
    release(slots)
    light = materialize(reps.join(crowd.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", "n_shingles", "sketch", "bands"), "sketches")
    asked = light.select("doc_id").join(one.select("doc_id", F.col("version").alias("own")), "doc_id")
    texts = docs.join(asked.hint("shuffle_hash"), "doc_id").filter("version = own")
    texts = materialize(texts.dropDuplicates(["doc_id"]).select("doc_id", "text"), "texts")

    def linked(pairs: DataFrame) -> DataFrame:
        near = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        near = near.join(light.select(F.col("doc_id").alias("a"), F.struct("n_shingles", "sketch").alias("x")), "a").join(light.select(F.col("doc_id").alias("b"), F.struct("n_shingles", "sketch").alias("y")), "b")
        return _confirm(near.filter(_plausible("x", "y", threshold)).select("a", "b"), texts, width, threshold)

    edges = materialize(linked(crowd.filter("doc_id <> p1").select(F.col("p1").alias("a"), F.col("doc_id").alias("b"))), "edges")
    for again in (True, False):
        comp = components(edges)
        known = materialize(crowd.join(comp.select(F.col("node").alias("doc_id"), F.col("component").alias("c")), "doc_id", "left").withColumn("c", F.coalesce("c", "doc_id")), "known")
        apart = known.groupBy("bucket").agg(F.min("c").alias("lo"), F.max("c").alias("hi"), F.count("*").alias("n")).filter("lo <> hi").select("bucket", "n")
        if again:
            # All members of such a bucket against its other chosen member, where they are not known to be linked.
            chosen = known.filter("doc_id = p2").select("bucket", F.col("c").alias("pc")).join(apart, "bucket")
            pairs = known.join(chosen, "bucket").filter(F.col("c") != F.col("pc")).select(F.col("p2").alias("a"), F.col("doc_id").alias("b"))
            more = linked(pairs)
        else:
            more = _links_apart(known, apart, light, texts, width, threshold)
        edges = materialize(edges.unionByName(more), "edges")
        release(known)
    comp = components(edges)
    # Members that stand for themselves need no row: only those of larger classes and those with links are looked up.
    above = comp.select(F.col("node").alias("doc_id"), F.col("component").alias("linked"))
    moved = member.join(above.select(F.col("doc_id").alias("rep"), "linked"), "rep", "left").select("doc_id", F.coalesce("linked", "rep").alias("linked"))
    moved = materialize(moved.unionByName(above.join(member, "doc_id", "left_anti")), "moved")
    out = sigs.select("doc_id", "n_shingles").join(moved, "doc_id", "left").withColumn("component_id", F.coalesce("linked", "doc_id"))
    return out.select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def op8_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), 2, THRESHOLD)


OP8_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws
  FROM documents),
s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) = 1 THEN [ws[1]]
    ELSE list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]) END) AS g FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
h AS (SELECT s.doc_id, g, n FROM s JOIN n USING (doc_id)),
i AS (SELECT x.doc_id AS a, y.doc_id AS b, x.n AS na, y.n AS nb, count(*) AS k
      FROM h x JOIN h y ON x.g = y.g AND x.doc_id < y.doc_id AND 100 * least(x.n, y.n) >= 80 * greatest(x.n, y.n)
      GROUP BY ALL),
e AS (SELECT a, b FROM i WHERE 100 * k >= 80 * (na + nb - k)),
l AS (SELECT a, b FROM e UNION SELECT b, a FROM e UNION SELECT a, a FROM e UNION SELECT b, b FROM e),
c(step, id, v) AS (
  SELECT 0, a, a FROM (SELECT DISTINCT a FROM l)
  UNION ALL SELECT step + 1, l.a, min(v) FROM c JOIN l ON c.id = l.b WHERE step < 64 GROUP BY step, l.a)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, coalesce(v, d.doc_id) AS component_id, d.doc_id = coalesce(v, d.doc_id) AS kept
FROM documents d LEFT JOIN n USING (doc_id) LEFT JOIN (SELECT id, v FROM c WHERE step = 64) x ON x.id = d.doc_id
"""
