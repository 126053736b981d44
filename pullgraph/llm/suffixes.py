"""Repeated passages across documents with a sparse suffix array over words.

Only suffixes at content-selected positions are kept: the position whose GRAM-word hash is smallest among `window`
neighbouring positions.  The choice depends on the words alone, so two copies of a passage keep the same suffixes: each
passage of `least` words belongs to one kept suffix, which has `prefix = least - window + 1` words of the passage after
it.  The passages of one suffix start at neighbouring words; all words they cover are its stretch.

1. The suffixes of all documents are sorted: by the identity of their prefix, then of their stretch, then by document and
   place.  The sort is one range exchange, so suffixes with one prefix stand together, and a prefix that a third of all
   documents share is spread over as many tasks as its rows need.
2. Neighbours are compared as they stream by: a run of suffixes with the same prefix from two documents is a match; so is,
   until its other part is known, a run that reaches the edge of a task.
3. Matches are extended to the left and to the right.  Where all suffixes of a prefix have the same stretch, they agree over
   all of it.  Where stretches differ, the window of `least` words is moved over each, word by word from the leftmost place
   that still holds the prefix to the rightmost, and each such passage is counted over all documents.  A repeat is a
   maximal run of words that such passages cover.

So the result is exact: a word is in a repeat if and only if a passage of `least` words around it stands as a whole in
another document.  Prefix and stretch, and passages, are told apart by 128 bits.  Passages are made once per different
stretch, `window` at most for each; counting is with map-side combining; no group is collected.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import materialize, release, scoped
from .common import Runs, U64, Words, arrow_map, batches, documents_of, join_texts, table, unused

LEAST = 50
WINDOW = 26
GRAM = 4


def _anchors(w: Words, least: int, window: int, gram: int) -> tuple[np.ndarray, ...]:
    """Of the kept suffixes of a batch: text number, prefix identity, first passage, passages, stretch identity."""
    total = len(w.start)
    if total < least:
        none = np.zeros(0, np.int64)
        return none, none.astype(U64), none, none, none.astype(U64)
    runs = Runs(w.hash)
    at = np.arange(total - least + 1)
    rank = runs.of(np.arange(total - least + window), gram)
    owner = np.repeat(np.arange(len(w.n)), w.n)
    fits = at + least <= w.first[1:][owner[: len(at)]]
    low = np.lib.stride_tricks.sliding_window_view(rank, window).argmin(axis=1) + at
    # The chosen place never goes back from one passage to the next, so the passages of a suffix are neighbours.
    start = np.flatnonzero(fits)
    chosen, head, n = np.unique(low[fits], return_index=True, return_counts=True)
    begin = start[head]
    return owner[chosen], runs.of(chosen, least - window + 1), begin, n, Runs(w.hash2).of(begin, n - 1 + least)


SUFFIX = "key long, stretch long, doc_id long, version int, start int, n int"
ORDER = ("key", "stretch", "doc_id", "start")


def suffixes(docs: DataFrame, least: int = LEAST, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """(key, stretch, doc_id, version, start, n) of each kept suffix of documents (doc_id, text, version): identities of
    prefix and stretch, and the first of its n passages in words."""

    def run(it):
        for b in batches(it, 1 << 19):
            w = Words(b.column(1).to_pylist())
            owner, key, begin, n, stretch = _anchors(w, least, window, gram)
            put = pa.array(owner)
            yield pa.RecordBatch.from_arrays(
                [pa.array(key.view(np.int64)), pa.array(stretch.view(np.int64)), b.column(0).take(put), b.column(2).take(put), pa.array((begin - w.first[owner]).astype(np.int32)), pa.array(n.astype(np.int32))],
                ["key", "stretch", "doc_id", "version", "start", "n"],
            )

    return arrow_map(docs.filter("doc_id IS NOT NULL"), run, SUFFIX)


def suffix_array(kept: DataFrame, partitions: int | None = None) -> DataFrame:
    """The suffixes in order, over as many tasks as asked for; equal prefixes stand together, in neighbouring tasks at worst."""
    n = partitions or int(kept.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return kept.repartitionByRange(n, *ORDER).sortWithinPartitions(*ORDER)


def matches(ordered: DataFrame) -> DataFrame:
    """The suffixes of suffix_array() whose neighbours with the same prefix are of two documents, or may be.

    A run of equal prefixes is passed on when a second document is met; what waits until then is of one document.  The
    first and the last run of a task are passed on in any case, as they may go on in another task.
    """

    def run(it):
        key, doc, shared, held = None, 0, False, []
        for b in it:
            if not b.num_rows:
                continue
            k, d = (b.column(i).to_numpy(zero_copy_only=False) for i in (0, 2))
            begin = np.concatenate([[0], np.flatnonzero(k[1:] != k[:-1]) + 1])
            stop = np.concatenate([begin[1:], [len(k)]])
            low, high = np.minimum.reduceat(d, begin), np.maximum.reduceat(d, begin)
            keep = low != high
            if key is None:
                keep[0] = True
            elif k[0] == key:
                keep[0] |= shared or low[0] != doc
                if keep[0]:
                    yield from held
            if len(begin) > 1 or keep[0] or k[0] != key:
                held = []
            key, doc, shared = int(k[-1]), int(d[-1]), bool(keep[-1])
            if not shared:
                held.append(b.slice(int(begin[-1])))
            yield b.filter(pa.array(np.repeat(keep, stop - begin)))
        yield from held

    return arrow_map(ordered, run, SUFFIX)


def _passages(asked: DataFrame, docs: DataFrame, least: int) -> DataFrame:
    """(key, stretch, i, lo, hi, p1, p2) of each passage of the asked (key, stretch, lo, hi, at: doc_id and start, n)."""

    def run(it):
        for batch in it:
            for b in batches([batch], 1 << 19):
                w = Words(b.column(1).to_pylist())
                one, two = Runs(w.hash), Runs(w.hash2)
                lists = b.column(2)
                flat, count = lists.flatten(), np.diff(lists.offsets.to_numpy())
                field = {k: flat.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in ("key", "stretch", "lo", "hi", "start", "n")}
                text = np.repeat(np.arange(len(count)), count)
                begin, n = w.first[:-1][text] + field["start"], field["n"]
                # Rows may share a doc_id: the asked one is that whose stretch is the asked one.
                there = begin + n - 1 + least <= w.first[1:][text]
                there[there] = two.of(begin[there], n[there] - 1 + least).view(np.int64) == field["stretch"][there]
                begin, n = begin[there], n[there]
                i = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
                s = np.repeat(begin, n) + i
                put = {k: pa.array(np.repeat(field[k][there], n)) for k in ("key", "stretch", "lo", "hi")}
                found = [pa.array(x.of(s, least).view(np.int64)) for x in (one, two)]
                yield pa.RecordBatch.from_arrays([put["key"], put["stretch"], pa.array(i.astype(np.int32)), put["lo"], put["hi"], *found], ["key", "stretch", "i", "lo", "hi", "p1", "p2"])

    wants = asked.groupBy("at.doc_id").agg(F.collect_list(F.struct("key", "stretch", "lo", "hi", "at.start", "n")).alias("wants"))
    src = join_texts(docs, materialize(wants, "wants"), "wants").select("doc_id", "text", "wants")
    return arrow_map(src, run, "key long, stretch long, i int, lo long, hi long, p1 long, p2 long")


SPANS = "doc_id long, version int, repeats array<struct<start:int,stop:int>>, later array<struct<start:int,stop:int>>, repeat_words long, later_words long"


def _united(text: np.ndarray, start: np.ndarray, stop: np.ndarray, texts: int) -> tuple[pa.Array, pa.Array]:
    """(spans of each text, words in them) of [start, stop) by text number, where spans that overlap or touch are one."""
    order = np.lexsort((start, text))
    text, start, stop = text[order], start[order], stop[order]
    # One number line for all texts, on which no span of a text reaches the next one's.
    far = text * (int(stop.max(initial=0)) + 1)
    reach = np.maximum.accumulate(far + stop)
    head = np.flatnonzero(np.concatenate([[True], (far + start)[1:] > reach[:-1]])) if len(text) else np.zeros(0, np.int64)
    owner, low = text[head], start[head]
    high = (reach - far)[np.concatenate([head[1:], [len(text)]]) - 1] if len(text) else low
    offsets = np.searchsorted(owner, np.arange(texts + 1))
    words = np.concatenate([[0], np.cumsum(high - low)])[offsets]
    spans = pa.StructArray.from_arrays([pa.array(low, pa.int32()), pa.array(high, pa.int32())], ["start", "stop"])
    return pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), spans), pa.array(np.diff(words), pa.int64())


def _version(docs: DataFrame) -> Column:
    """Tells texts of rows with one doc_id apart."""
    return F.hash(F.coalesce(docs["text"].cast("string"), F.lit(""))).alias("version")


@scoped
def repeated_passages(docs: DataFrame, least: int = LEAST, window: int = WINDOW, gram: int = GRAM) -> DataFrame:
    """One row per document that holds a passage standing in another document too.

    repeats: its spans in words, [start, stop); later: the spans that also stand in a document with a smaller doc_id,
    which a caller may cut and still keep one copy; and the words in either.  Words are `[^\\x20\\x09-\\x0D]+`, compared
    exactly.  Documents without such a passage, null, empty and short texts have no row; neither have rows without
    doc_id.  Rows that repeat a doc_id are one document: what they share is no repeat; if their texts differ, each text
    with a repeat has a row, told apart by version, a hash of the text.  Repeats within one document alone do not count.
    Extra columns are dropped.  An empty table gives no rows.
    """
    if not 0 < window <= least or gram > least - window + 1:
        raise ValueError("window must be between 1 and least, and a gram must fit into the prefix")
    docs = documents_of(docs, _version(docs))
    kept = materialize(suffixes(docs, least, window, gram), "suffixes")
    hits = materialize(matches(suffix_array(kept)), "matches")
    release(kept)
    stretches = materialize(hits.groupBy("key", "stretch", "n").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), F.min(F.struct("doc_id", "start")).alias("at")), "stretches")
    # Written, so that the joins have a shuffle of their own on either side, whose large partitions can be split.
    keys = materialize(stretches.groupBy("key").agg(F.min("lo").alias("first"), F.max("hi").alias("last"), F.count("*").alias("k")).filter("first <> last"), "keys")
    single = stretches.join(keys.filter("k = 1").select("key"), "key", "left_semi").select("key", "stretch", F.lit(0).alias("i"), "n", "lo", "hi")
    passages = materialize(_passages(stretches.join(keys.filter("k > 1").select("key"), "key", "left_semi"), docs, least), "passages")
    agreed = materialize(passages.groupBy("p1", "p2").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")).filter("lo <> hi"), "agreed")
    # Neighbouring passages of a stretch with the same documents are one range.
    found = passages.select("key", "stretch", "i", "p1", "p2").join(agreed, ["p1", "p2"]).groupBy("key", "stretch", "lo", "hi").agg(F.sort_array(F.collect_set("i")).alias("at"))
    numbered = found.select("key", "stretch", "lo", "hi", F.posexplode("at").alias("k", "i"))
    ranges = numbered.groupBy("key", "stretch", "lo", "hi", (F.col("i") - F.col("k")).alias("g")).agg(F.min("i").alias("i"), F.count("*").cast("int").alias("n")).drop("g")
    parts = materialize(single.unionByName(ranges), "parts").groupBy("key", "stretch").agg(F.collect_list(F.struct("i", "n", "lo", "hi")).alias("parts"))
    parts = materialize(parts, "ranges")
    places = hits.select("key", "stretch", "doc_id", "version", "start").join(parts, ["key", "stretch"]).select("doc_id", "version", "start", F.explode("parts").alias("p"))
    spans = places.select("doc_id", "version", (F.col("start") + F.col("p.i")).alias("start"), (F.col("start") + F.col("p.i") + F.col("p.n") + F.lit(least - 1)).alias("stop"), (F.col("p.lo") < F.col("doc_id")).cast("int").alias("kind"))

    def merge(it):
        for b in it:
            lists = b.column(2)
            flat, count = lists.flatten(), np.diff(lists.offsets.to_numpy())
            start, stop, kind = (flat.field(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in ("start", "stop", "kind"))
            text = np.repeat(np.arange(b.num_rows), count)
            cols = [_united(*(x[pick] for x in (text, start, stop)), b.num_rows) for pick in (slice(None), kind == 1)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), *(c[0] for c in cols), *(c[1] for c in cols)], ["doc_id", "version", "repeats", "later", "repeat_words", "later_words"])

    grouped = spans.groupBy("doc_id", "version").agg(F.collect_list(F.struct("start", "stop", "kind")).alias("spans"))
    return arrow_map(grouped, merge, SPANS)


def cut_passages(docs: DataFrame, passages: DataFrame) -> DataFrame:
    """docs with the `later` spans taken out of text and n_chars set anew; other columns as they were.

    A cut goes from the first byte of its first word to the first byte of the word after it.  A document of which no
    word is left is dropped; one that had no word from the start, or no text or doc_id, is kept as it is.  Rows that repeat
    a doc_id and text are all cut; rows with the same doc_id and another text have cuts of their own.  An empty table
    gives none.
    """
    names = docs.columns

    def run(it):
        for batch in it:
            for b in batches([batch], 1 << 19):
                texts, cuts = b.column(b.schema.get_field_index("text")).to_pylist(), b.column(b.num_columns - 1).to_pylist()
                w = Words(texts)
                data = w.data.tobytes()
                out, keep = [], []
                for i, (t, spans) in enumerate(zip(texts, cuts, strict=True)):
                    if spans:
                        first, stop = int(w.first[i]), int(w.first[i + 1])
                        base, end = int(w.base[i]), int(w.base[i + 1]) - 1
                        parts, at = [], base
                        for s in spans:
                            parts.append(data[at : int(w.start[first + s["start"]])])
                            at = int(w.start[first + s["stop"]]) if first + s["stop"] < stop else end
                        t = b"".join([*parts, data[at:end]]).decode("utf-8", "replace")
                    out.append(t)
                    keep.append(not spans or bool(t.strip(" \t\n\x0b\x0c\r")))
                cols = {n: b.column(n) for n in names}
                cols["text"] = pa.array(out, pa.string())
                if "n_chars" in cols:
                    cols["n_chars"] = pa.array([o if not s else len(t) for o, s, t in zip(cols["n_chars"].to_pylist(), cuts, out, strict=True)], cols["n_chars"].type)
                yield pa.RecordBatch.from_arrays([cols[n] for n in names], names).filter(pa.array(keep))

    key, version, cut = (unused(names, x) for x in ("__id", "__version", "__cut"))
    cuts = passages.filter("later_words > 0").select(F.col("doc_id").alias(key), F.col("version").alias(version), F.col("later").alias(cut))
    # The same way at every size: what is cut grows with the documents.
    src = docs.join(cuts.hint("shuffle_hash"), (docs["doc_id"] == F.col(key)) & (_version(docs) == F.col(version)), "left").drop(key, version)
    return arrow_map(src, run, docs.schema.simpleString().removeprefix("struct<").removesuffix(">"))


def op2_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_passages(table(spark, sf_dir, "documents"))
