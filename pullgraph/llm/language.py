"""Language identification with a bidirectional gated recurrent network over bytes, in numpy.

The network reads all bytes of a text forwards and backwards, ASCII letters in lower case, and a softmax over both hidden
states labels every byte position: letters, digits, signs and white space alike.  A document's probabilities are the mean
over all its positions.

States run across words.  So that texts of any length are read side by side, a text is cut into stretches of STRETCH
bytes, each of which is read with CONTEXT bytes of the text before and after it; the states have forgotten what is further
away, and every position counts once, in the stretch it belongs to.

Training is backpropagation through time with Adam on a bounded sample of labelled documents: TRAIN_DOCUMENTS rows,
shared out evenly among the languages, with the smallest hashes of each, and WINDOWS stretches of WINDOW characters spread
over the whole text of each.  Its cost does not depend on the size of the corpus.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as Over
from pyspark.sql import functions as F

from .common import arrow_map, batches, documents_of, table

TRAIN_DOCUMENTS = 1500
#: Stretches of a training document, and characters of each.
WINDOWS, WINDOW = 12, 64
STEPS = 500
BATCH = 192
HIDDEN, EMBED = 10, 12
#: Bytes that are read side by side as one row, and bytes of the same text that are read before and after them.
STRETCH, CONTEXT = 512, 64
#: Numbers in the arrays of one group of stretches.
CELLS = 6_000_000
UNDETERMINED = "und"
#: Groups that the rows of one language are dealt to before the smallest hashes of all are chosen.
SALTS = 64

ANY_LETTER = regex.compile(r"\p{L}").search
PADDING = 256
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def _sigmoid_in(x: np.ndarray) -> None:
    """Logistic function in place."""
    x *= 0.5
    np.tanh(x, out=x)
    x += 1.0
    x *= 0.5


@dataclass
class Network:
    """Weights; labels has the learned languages in order.  States and gates are arrays (unit, row)."""

    labels: list[str]
    w: dict[str, np.ndarray]

    @classmethod
    def fresh(cls, labels: list[str], seed: int = 7) -> Network:
        rng = np.random.default_rng(seed)
        draw = lambda *shape: (rng.standard_normal(shape) / np.sqrt(shape[0])).astype(np.float32)
        w = {"emb": draw(257, EMBED) * 4, "out": draw(2 * HIDDEN, len(labels)), "out_b": np.zeros(len(labels), np.float32)}
        for d in "fb":
            w |= {f"x{d}": draw(EMBED, 3 * HIDDEN), f"h{d}": draw(HIDDEN, 3 * HIDDEN), f"b{d}": np.zeros(3 * HIDDEN, np.float32)}
        return cls(labels, w)

    def _direction(self, ids: np.ndarray, mask: np.ndarray, d: str, see: Callable, keep: list | None = None) -> None:
        """Calls see(time, states) along one direction; ids, mask (time, row).  Padding sets a state back to zero."""
        w, two = self.w, 2 * HIDDEN
        rows = np.ascontiguousarray((w["emb"] @ w[f"x{d}"] + w[f"b{d}"]).T)
        recurrent = np.ascontiguousarray(w[f"h{d}"].T)
        whole = mask.all(axis=1)
        h = np.zeros((HIDDEN, ids.shape[1]), rows.dtype)
        for t in range(len(ids)) if d == "f" else range(len(ids) - 1, -1, -1):
            gx, gh = np.take(rows, ids[t], axis=1, mode="clip"), recurrent @ h
            zr = gx[:two]
            zr += gh[:two]
            _sigmoid_in(zr)
            z, r, c = zr[:HIDDEN], zr[HIDDEN:], gx[two:]
            c += gh[two:] * r
            np.tanh(c, out=c)
            new = h - c
            new *= z
            new += c
            if not whole[t]:
                new *= mask[t]
            if keep is not None:
                keep.append((t, h, z, r, c, gh[two:]))
            h = new
            see(t, h)

    def positions(self, ids: np.ndarray, mask: np.ndarray) -> np.ndarray:
        """Label probabilities of every position (time, label, row)."""
        s = np.empty((len(ids), len(self.labels), ids.shape[1]), self.w["out"].dtype)
        s[:] = self.w["out_b"][:, None]
        for k, d in enumerate("fb"):
            part = np.ascontiguousarray(self.w["out"][k * HIDDEN : (k + 1) * HIDDEN].T)

            def see(t, h, part=part):
                s[t] += part @ h

            self._direction(ids, mask, d, see)
        s -= s.max(axis=1, keepdims=True)
        np.exp(s, out=s)
        s /= s.sum(axis=1, keepdims=True)
        return s

    def gradients(self, ids: np.ndarray, mask: np.ndarray, label: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Mean cross entropy over positions and its gradient by backpropagation through time."""
        w, kept = self.w, {"f": [], "b": []}
        hidden = np.zeros((len(ids), 2 * HIDDEN, ids.shape[1]), w["out"].dtype)
        for k, d in enumerate("fb"):

            def see(t, h, k=k):
                hidden[t, k * HIDDEN : (k + 1) * HIDDEN] = h

            self._direction(ids, mask, d, see, kept[d])
        s = np.matmul(w["out"].T, hidden) + w["out_b"][:, None]
        e = np.exp(s - s.max(axis=1, keepdims=True))
        p = e / e.sum(axis=1, keepdims=True)
        total = float(mask.sum())
        right = np.arange(len(label))
        loss = float(-(np.log(p[:, label, right] + 1e-9) * mask).sum() / total)
        p[:, label, right] -= 1
        p *= mask[:, None, :] / total
        g = {k: np.zeros_like(v) for k, v in w.items()}
        g["out"] = np.tensordot(hidden, p, axes=([0, 2], [0, 2]))
        g["out_b"] = p.sum(axis=(0, 2))
        dh_all = np.matmul(w["out"], p)
        for k, d in enumerate("fb"):
            back = np.zeros((HIDDEN, ids.shape[1]), w["out"].dtype)
            steps = np.zeros((len(ids), 3 * HIDDEN, ids.shape[1]), w["out"].dtype)
            for t, h, z, r, c, ghc in reversed(kept[d]):
                dh = (dh_all[t, k * HIDDEN : (k + 1) * HIDDEN] + back) * mask[t]
                dz, dc = dh * (h - c) * z * (1 - z), dh * (1 - z) * (1 - c * c)
                dr = dc * ghc * r * (1 - r)
                steps[t] = np.concatenate([dz, dr, dc])
                dgh = np.concatenate([dz, dr, dc * r])
                g[f"h{d}"] += h @ dgh.T
                back = dh * z + w[f"h{d}"] @ dgh
            flat = ids.ravel()
            by_byte = np.stack([np.bincount(flat, weights=steps[:, u].ravel(), minlength=257) for u in range(3 * HIDDEN)]).astype(w["out"].dtype)
            g[f"x{d}"] = (by_byte @ w["emb"]).T
            g[f"b{d}"] = by_byte.sum(axis=1)
            g["emb"] += by_byte.T @ w[f"x{d}"].T
        return loss, g

    def train(self, stretches: list[bytes], label: np.ndarray, steps: int = STEPS, batch: int = BATCH, rate: float = 0.015, seed: int = 3) -> list[float]:
        rng = np.random.default_rng(seed)
        m, v = ({k: np.zeros_like(x) for k, x in self.w.items()} for _ in range(2))
        losses = []
        # Each language is drawn equally often, so that rare ones are learned too.
        by = [np.flatnonzero(label == k) for k in range(len(self.labels))]
        for step in range(1, steps + 1):
            pick = np.concatenate([rng.choice(x, -(-batch // len(by))) for x in by])
            ids, mask = padded([stretches[i] for i in pick])
            loss, g = self.gradients(ids, mask, label[pick])
            losses.append(loss)
            slow = rate * min(1.0, step / 30) * (1 - 0.9 * step / steps)
            for k in self.w:
                m[k] += 0.1 * (g[k] - m[k])
                v[k] += 0.01 * (g[k] ** 2 - v[k])
                self.w[k] = (self.w[k] - slow * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
        return losses


def encoded(text: str) -> np.ndarray:
    """Bytes of a text as the network reads them."""
    return LOWER[np.frombuffer(text.encode("utf-8", "replace"), np.uint8)]


def padded(stretches: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(time, row) byte ids and the mask of real positions."""
    n = max(map(len, stretches), default=0)
    ids = np.full((n, len(stretches)), PADDING, np.int64)
    mask = np.zeros((n, len(stretches)), np.float32)
    for i, x in enumerate(stretches):
        ids[: len(x), i] = np.frombuffer(x, np.uint8)
        mask[: len(x), i] = 1
    return ids, mask


class Reader:
    """Reads whole texts with one network."""

    def __init__(self, net: Network) -> None:
        self.net = net

    def _groups(self, raw: list[np.ndarray]):
        """(number of the text, first position, counted (time, row), ids, mask) of groups of stretches of similar length."""
        size = np.array([len(r) for r in raw], np.int64)
        per = -(-size // STRETCH)
        text = np.repeat(np.arange(len(raw)), per)
        if not len(text):
            return
        data = np.concatenate([*raw, np.zeros(1, np.uint8)])
        base = (np.cumsum(size) - size)[text]
        at = (np.arange(len(text)) - np.repeat(np.cumsum(per) - per, per)) * STRETCH
        low, high = np.maximum(at - CONTEXT, 0), np.minimum(at + STRETCH + CONTEXT, size[text])
        order = np.argsort(high - low, kind="stable")[::-1]
        first = 0
        while first < len(order):
            longest = int((high - low)[order[first]])
            pick = order[first : first + max(16, CELLS // (longest * max(len(self.net.labels), 3)))]
            first += len(pick)
            place = np.arange(longest)[:, None]
            inside = place < (high - low)[pick]
            ids = np.where(inside, data[np.minimum(base[pick] + low[pick] + place, len(data) - 1)], PADDING)
            begin = (at - low)[pick]
            yield text[pick], low[pick], (place >= begin) & (place < begin + STRETCH) & inside, ids, inside.astype(np.float32)

    def probabilities(self, texts: list[str | None]) -> np.ndarray:
        """(text, label) mean over all positions of each text; zeros for a text without a letter."""
        raw = [encoded(t) if t and ANY_LETTER(t) else np.zeros(0, np.uint8) for t in texts]
        total = np.zeros((len(texts), len(self.net.labels)))
        for text, _, counted, ids, mask in self._groups(raw):
            p = self.net.positions(ids, mask)
            p *= counted[:, None, :]
            np.add.at(total, text, p.sum(axis=0, dtype=np.float64).T)
        return total / np.maximum([[len(r)] for r in raw], 1) if len(raw) else total

    def label_positions(self, text: str) -> list[str]:
        """The likeliest language at every byte of one text."""
        raw = encoded(text)
        out = np.zeros(len(raw), np.int64)
        for _, low, counted, ids, mask in self._groups([raw]):
            best = self.net.positions(ids, mask).argmax(axis=1)
            t, row = np.nonzero(counted)
            out[low[row] + t] = best[t, row]
        return [self.net.labels[k] for k in out]

    def read(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        """Likeliest language of each text and its pooled probability; ties go to the first in the order of labels."""
        if not self.net.labels:
            return [UNDETERMINED] * len(texts), [0.0] * len(texts)
        p = self.probabilities(texts)
        best = p.argmax(axis=1) if len(p) else []
        score = [min(1.0, float(p[i, k])) for i, k in enumerate(best)]
        return [self.net.labels[k] if s > 0 else UNDETERMINED for k, s in zip(best, score, strict=True)], score


def level(counts: list[int], most: int) -> int:
    """Largest number, 1 at least, that each of the groups can give, or all it has, with no more than `most` in all."""
    low, high = 1, max([1, *counts])
    while low < high:
        mid = (low + high + 1) // 2
        low, high = (mid, high) if sum(min(c, mid) for c in counts) <= most else (low, mid - 1)
    return low


def fit(labelled: DataFrame, documents: int = TRAIN_DOCUMENTS, windows: int = WINDOWS, steps: int = STEPS) -> Network:
    """Train on (doc_id, text, lang) rows: a bounded sample with the smallest hashes of each lang, ties by doc_id.

    Rows with a null text or lang, or a text without a letter, are no examples.  No examples: a network without labels,
    which answers `und`.
    """
    pick = labelled.filter(F.col("text").rlike(r"\p{L}") & F.col("lang").isNotNull()).select("doc_id", "text", "lang", F.xxhash64("doc_id").alias("h"))
    # The text stays out of the sort; only the chosen rows bring theirs, cut to stretches before they leave the executors.
    # Each task passes on its first rows of every lang and salt alone, and each salt its first of a lang, so that one
    # language's rows are spread however many tasks there are.
    counts = [r["count"] for r in pick.groupBy("lang").count().collect()]
    most = level(counts, documents)
    first = lambda df, *by: df.withColumn("place", F.row_number().over(Over.partitionBy(*by).orderBy("h", "doc_id"))).filter(F.col("place") <= most)
    salted = pick.select("h", "doc_id", "lang", F.pmod(F.xxhash64("h"), F.lit(SALTS)).alias("salt"))
    ids = first(first(salted, "lang", "salt").drop("place"), "lang")
    documents = max(documents, len(counts))
    step = F.greatest(F.lit(WINDOW), F.floor(F.char_length("text") / windows))
    starts = F.slice(F.sequence(F.lit(0).cast("long"), F.char_length("text").cast("long"), step.cast("long")), 1, windows)
    cut = F.transform(starts, lambda i: F.substring("text", (i + 1).cast("int"), F.lit(WINDOW)))
    rows = pick.join(F.broadcast(ids.select("doc_id", "lang").distinct()), ["doc_id", "lang"], "left_semi").select("h", "doc_id", "lang", cut.alias("w")).orderBy("h", "doc_id").limit(documents).collect()
    labels = sorted({r["lang"] for r in rows})
    net = Network.fresh(labels)
    examples = [(encoded(w).tobytes(), labels.index(r["lang"])) for r in rows for w in r["w"] if w]
    if labels:
        net.train([w for w, _ in examples], np.array([k for _, k in examples]), steps)
    return net


def predict(docs: DataFrame, net: Network) -> DataFrame:
    """doc_id, lang_pred, score of every whole text.

    `und` with score 0 where the text is null or has no letter, or nothing was learned.  Extra columns are dropped, rows
    that repeat are answered each time, an empty table gives none.
    """

    def run(it):
        reader = Reader(net)
        for b in batches(it, 1 << 20):
            labels, scores = reader.read(b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(labels, pa.string()), pa.array(scores, pa.float64())], ["doc_id", "lang_pred", "score"])

    return arrow_map(documents_of(docs), run, "doc_id long, lang_pred string, score double")


#: A document is rejected if no language was found or its pooled probability is no more than this part of the way from
#: what an even guess among the learned labels has to 1.
MARGIN = 0.04


def least_score(labels: int, margin: float = MARGIN) -> float:
    """Smallest pooled probability that identifies one of so many labels; with one label any text with a letter has it."""
    return 1 / labels + margin * (1 - 1 / labels) - 1e-6 if labels else 1.0


def keep_identified(docs: DataFrame, net: Network, margin: float = MARGIN) -> DataFrame:
    """docs whose language was identified, all columns as they were but for a null lang, which is filled in.

    One pass over the rows, no shuffle; texts are judged whole.  Nulls and texts without a letter are rejected.
    """
    names, min_score = docs.columns, least_score(len(net.labels), margin)

    def run(it):
        reader = Reader(net)
        for b in batches(it, 1 << 20):
            labels, scores = reader.read(b.column(b.schema.get_field_index("text")).to_pylist())
            cols = {n: b.column(n) for n in names}
            if "lang" in cols:
                cols["lang"] = pa.array([x if x is not None else y for x, y in zip(cols["lang"].to_pylist(), labels, strict=True)], pa.string())
            keep = [x != UNDETERMINED and s >= min_score for x, s in zip(labels, scores, strict=True)]
            yield pa.RecordBatch.from_arrays([cols[n] for n in names], names).filter(pa.array(keep, pa.bool_()))

    return arrow_map(docs, run, docs.schema.simpleString().removeprefix("struct<").removesuffix(">"))


def held_out() -> Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    net = fit(docs.filter(~held_out()).select("doc_id", "text", "lang"))
    return predict(docs, net).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
