"""Quality rules from a suffix array over words.

All texts of a slice are laid end to end and share one suffix array, built by prefix doubling on the numbers of the words,
which are told apart by their bytes; a suffix starts with its text's number, so suffixes of different texts never stand
between each other, and only suffixes that are not told apart yet are sorted again.  Longest common prefixes between
neighbours are read off the ranks of the doubling steps, longest step first, and are exact.  The intervals of that array are
the maximal repeated substrings: a suffix that shares `n` words with a neighbour starts a repeat of n words.  The union of
the spans of repeats gives the covered fraction, the largest value the longest repeat.

Memory is one slice of texts, or one text, and 4 bytes a word for each doubling of its longest repeat.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import Words, arrow_map, batches, documents_of, numbered, table

#: Words of a window that counts as repeated in the base rule.
BASE_WINDOW = 8
MIN_WORDS = 20
MAX_REPEAT_PERCENT = 30
#: The method's own limits: a repeat has LEAST_REPEAT words at least; the union of repeats covers MAX_COVERED of the
#: words at most; the longest repeat has MAX_LONGEST words and MAX_LONGEST_SHARE of the text's words at most.
LEAST_REPEAT = 4
MAX_COVERED = 0.5
MAX_LONGEST = 150
MAX_LONGEST_SHARE = 0.1
SYMBOLS = np.zeros(256, bool)
SYMBOLS[[ord(c) for c in "#*$%&|<>"]] = True


def suffix_array(tokens: np.ndarray, owner: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, longest common prefix) of all suffixes, each ending where its owner's text ends.

    tokens: one number per word; owner: the text's number per word, ascending.  order[i] is the start of the i-th
    smallest suffix; lcp[i] the words that suffixes order[i - 1] and order[i] share (0 at the first and between texts).
    """
    n = len(tokens)
    if n == 0:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    key = owner.astype(np.int64) * (int(tokens.max()) + 2) + tokens + 1
    order = np.argsort(key, kind="stable")
    sorted_key = key[order]
    head = np.concatenate([[True], sorted_key[1:] != sorted_key[:-1]])
    # rank: place of the first suffix of the group, so that groups can be split without renaming others.
    rank = np.empty(n, np.int64)
    rank[order] = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    end = np.searchsorted(owner, owner, side="right")  # end of each position's text
    kind = np.int32 if n < 2**31 else np.int64
    levels = [rank.astype(kind)]  # ranks by the first 1, 2, 4, ... words
    step = 1
    open_ = _open(head)
    while len(open_):
        at = order[open_]
        ahead = at + step
        inside = ahead < end[at]
        second = np.where(inside, rank[np.minimum(ahead, n - 1)] + 1, 0)
        group = rank[at]
        sub = np.lexsort((second, group))
        order[open_] = at[sub]
        group, second = group[sub], second[sub]
        head[open_] = np.concatenate([[True], (group[1:] != group[:-1]) | (second[1:] != second[:-1])])
        first = np.maximum.accumulate(np.where(head[open_], open_, 0))
        rank[order[open_]] = first
        open_ = _open(head)
        step *= 2
        levels.append(rank.astype(kind))
    return order, _lcp(order, end, levels)


def _open(head: np.ndarray) -> np.ndarray:
    """Places in groups of two or more."""
    single = head & np.concatenate([head[1:], [True]])
    return np.flatnonzero(~single)


def _lcp(order: np.ndarray, end: np.ndarray, levels: list[np.ndarray]) -> np.ndarray:
    """Shared words of neighbours: the ranks of level k are equal if and only if the first 2**k words are."""
    out = np.zeros(len(order), np.int64)
    todo = np.flatnonzero(levels[0][order[:-1]] == levels[0][order[1:]])
    if len(todo) == 0:
        return out
    a, b = order[todo], order[todo + 1]
    shared = np.zeros(len(todo), np.int64)
    for k in range(len(levels) - 1, -1, -1):
        x, y = a + shared, b + shared
        inside = (x < end[a]) & (y < end[b])
        rank = levels[k]
        shared += np.where(inside & (rank[np.where(inside, x, 0)] == rank[np.where(inside, y, 0)]), 1 << k, 0)
    out[todo + 1] = shared
    return out


def _covered(length: np.ndarray, owner: np.ndarray, texts: int) -> np.ndarray:
    """Words per text in the union of [i, i + length[i])."""
    n = len(length)
    edge = np.zeros(n + 1, np.int64)
    starts = np.flatnonzero(length)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + length[starts], -1)
    return np.bincount(owner[np.cumsum(edge[:-1]) > 0], minlength=texts)[:texts]


def measure(texts: list[str | None]) -> dict[str, np.ndarray]:
    """The base counts and the method's measures of each text."""
    w = Words(texts)
    n = len(texts)
    data, base = w.data, w.base
    owner = np.repeat(np.arange(n), w.n)
    begin = (data & 0xC0) != 0x80
    inside = np.zeros(len(data) + 1, np.int64)
    np.add.at(inside, w.start, 1)
    np.add.at(inside, w.stop, -1)
    word_chars = _sums((np.cumsum(inside[:-1]) > 0) & begin, base)
    symbols = _sums(SYMBOLS[data], base)
    order, lcp = suffix_array(w.number, owner)
    shared = np.zeros(len(order), np.int64)
    shared[order] = np.maximum(lcp, np.concatenate([lcp[1:], [0]])) if len(order) else lcp
    window = np.where(shared >= BASE_WINDOW, BASE_WINDOW, 0)
    repeats = np.where(shared >= LEAST_REPEAT, shared, 0)
    longest = np.zeros(n, np.int64)
    np.maximum.at(longest, owner, shared)
    return {
        "n_words": w.n.astype(np.int64),
        "word_chars": word_chars,
        "n_symbols": symbols,
        "n_dup_lines": _dup_lines(w, n),
        "n_repeat_words": _covered(window, owner, n),
        "covered_words": _covered(repeats, owner, n),
        "longest_repeat": longest,
    }


def _sums(flags: np.ndarray, base: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(flags)])
    return (total[base[1:]] - total[base[:-1]]).astype(np.int64)


def _dup_lines(w: Words, n: int) -> np.ndarray:
    """Lines with a word that equal an earlier line of their text."""
    data = w.data
    if len(data) == 0:
        return np.zeros(n, np.int64)
    stop = np.flatnonzero(data == 10)
    start = np.concatenate([[0], stop[:-1] + 1])
    has = np.searchsorted(w.start, stop) > np.searchsorted(w.start, start)
    start, stop = start[has], stop[has]
    line = numbered(data, start, stop)[0]
    owner = np.searchsorted(w.base, start, side="right") - 1
    if len(line) == 0:
        return np.zeros(n, np.int64)
    order = np.lexsort((line, owner))
    line, owner = line[order], owner[order]
    again = (line[1:] == line[:-1]) & (owner[1:] == owner[:-1])
    return np.bincount(owner[1:][again], minlength=n).astype(np.int64)


def verdicts(m: dict[str, np.ndarray], max_covered: float = MAX_COVERED, max_longest: int = MAX_LONGEST, max_share: float = MAX_LONGEST_SHARE) -> tuple[np.ndarray, np.ndarray]:
    """(base_failed, kept)."""
    n = m["n_words"]
    failed = (n < MIN_WORDS) | (100 * m["n_repeat_words"] > MAX_REPEAT_PERCENT * n)
    long_ = m["longest_repeat"] > max_longest + max_share * n
    return failed, ~(failed | (m["covered_words"] > max_covered * n) | long_)


SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, covered_words long, longest_repeat long, base_failed boolean, kept boolean"


def quality(docs: DataFrame, **limits: float) -> DataFrame:
    """Counts, measures and verdict of every document.

    Null and empty texts have no words and fail the base rule.  Ties do not arise: every number is a count.  Rows that repeat give repeated results; a null doc_id is
    kept; other columns are dropped; an empty table gives none.  A text longer than a slice is measured whole.
    """
    names = [x.split()[0] for x in SCHEMA.split(", ")]

    def run(it):
        for b in batches(it, 1 << 20):
            m = measure(b.column(1).to_pylist())
            failed, kept = verdicts(m, **limits)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(m[k]) for k in names[1:8]), pa.array(failed), pa.array(kept)], names)

    return arrow_map(documents_of(docs), run, SCHEMA)


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality(table(spark, sf_dir, "documents"))
