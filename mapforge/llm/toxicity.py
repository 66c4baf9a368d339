"""Operator 4: toxicity by compression distance between zstandard dictionaries.

Two dictionaries are trained by zstandard, one on the windows of toxic documents and one on those of
ordinary documents. A second pair has the same neutral part on both sides, the common words of ordinary
documents, and on the toxic side the segments that toxic documents have and ordinary ones lack, so that
a window of neutral text costs about the same with either. A document is cut into windows at white space;
each window is compressed with both sides of both pairs, and what the toxic side saves, in bytes, is the
window's distance in that pair. A logistic curve over the document's distances gives the score. It is
fitted on distances that each half of the training sample has in dictionaries of the other half, so no
text is judged by a dictionary it is part of; the score's 0.5 lies where the shares of missed toxic and of
``FALSE_COST`` times the rejected clean documents are least.

The training sample is bounded: whole documents of a class, at most ``SAMPLE_DOCS``, until ``SAMPLE_CHARS`` are reached; scoring
covers every whole text and never looks at labels, languages, sources or ids. Null text counts as
empty; an empty text has no window and gets score 0. Rows that repeat are scored alike, very long texts window
by window. With no labelled rows of either class, or an empty table, every score is 0. Columns other than ``score`` stay.
"""

from __future__ import annotations

import pickle
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mapforge.llm.common import table

SAMPLE_DOCS = 2000
SAMPLE_CHARS = 2_500_000
#: How much worse than a missed share of toxic documents an equal share of rejected clean ones is.
FALSE_COST = 4.0
WINDOW = 64
LEVEL = 5
BASE_BYTES = 24_000
OWN_BYTES = 8_000
TRAINED_BYTES = 110_000
SLICE_ROWS = 256
#: How matches are searched for: of the segments all, of the trained pair, which is longer, the likely ones.
THOROUGH, QUICK = zstandard.STRATEGY_BTLAZY2, zstandard.STRATEGY_LAZY
RAW, AUTO = zstandard.DICT_TYPE_RAWCONTENT, zstandard.DICT_TYPE_AUTO
HELD_OUT_FOLD, FOLDS = 0, 5


def fold(doc_id: str = "doc_id"):
    """The fold of a document: rows of fold 0 are never learned from."""
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(FOLDS))


def windows(text: str, size: int = WINDOW) -> list[bytes]:
    """Pieces of ``size`` bytes or a little more that end at white space; very long words are cut."""
    raw = text.lower().encode()
    return [m.group() for m in re.finditer(rb"(?s).{1,%d}(?:[^\s]{0,%d})" % (size, size // 2), raw)]


def _grams(texts: list[str], lengths: range = range(4, 10)) -> Counter:
    """In how many texts each short run of letters within a word occurs."""
    found: Counter = Counter()
    for t in texts:
        seen = set()
        for w in set(re.findall(r"\w+", t.lower())):
            w = f" {w} "
            for n in lengths:
                seen.update(w[i : i + n] for i in range(max(0, len(w) - n + 1)))
        found.update(seen)
    return found


def _typical(texts: list[str], other: Counter, n_other: int, budget: int) -> bytes:
    """Segments of letters that cover the texts while ordinary texts hardly have them: best last.

    Greedy cover: each step takes the segment found in most texts that are covered less than three times,
    counting long ones more, so that few segments stand for many spellings.
    """
    n = len(texts)
    own = _grams(texts)
    least = max(3, n // 50)
    good = {g for g, c in own.items() if c >= least and (other[g] + 0.5) / n_other * 15 <= c / n}
    has = []
    for t in texts:
        words = {f" {w} " for w in re.findall(r"\w+", t.lower())}
        has.append({w[i : i + k] for w in words for k in range(4, 10) for i in range(max(0, len(w) - k + 1))} & good)
    need, gain, kept, size = [3] * n, Counter(), [], 0
    for h in has:
        gain.update(h)
    while gain and size < budget:
        best = max(gain, key=lambda g: (gain[g] * (len(g) - 3), g))
        if gain[best] < least:
            del gain[best]
            continue
        kept.append(best)
        size += len(best.encode())
        for k, h in enumerate(has):
            if best in h:
                h.discard(best)
                need[k] -= 1
                if need[k] == 0:
                    gain.subtract(h)
        del gain[best]
    return "".join(reversed(kept)).encode()


def _trained(texts: list[str], size: int = TRAINED_BYTES) -> bytes:
    """A zstandard dictionary trained on all windows of the texts; the windows themselves where they are too few to train on."""
    samples = [w for t in texts for w in windows(t)]
    try:
        return zstandard.train_dictionary(size, samples, k=50, d=6).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[-size:]


@dataclass
class Model:
    toxic: bytes = b""
    ordinary: bytes = b""
    weights: list[float] = field(default_factory=list)
    trained_toxic: bytes = b""
    trained_ordinary: bytes = b""

    def __post_init__(self) -> None:
        self._made: tuple | None = None

    def __getstate__(self) -> tuple:
        return self.toxic, self.ordinary, self.weights, self.trained_toxic, self.trained_ordinary

    def __setstate__(self, state: tuple) -> None:
        self.toxic, self.ordinary, self.weights, self.trained_toxic, self.trained_ordinary = state
        self._made = None

    def compressors(self) -> tuple:
        if self._made is None:
            made = []
            for content, kind, strategy in ((self.toxic, RAW, THOROUGH), (self.ordinary, RAW, THOROUGH), (self.trained_toxic, AUTO, QUICK), (self.trained_ordinary, AUTO, QUICK)):
                params = zstandard.ZstdCompressionParameters.from_level(LEVEL, write_content_size=0, write_checksum=0, write_dict_id=0, min_match=4, strategy=strategy)
                d = zstandard.ZstdCompressionDict(content, dict_type=kind)
                d.precompute_compress(compression_params=params)
                made.append(zstandard.ZstdCompressor(dict_data=d, compression_params=params).compress)
            self._made = tuple(made)
        return self._made

    def distances(self, text: str) -> tuple[list[int], list[int]]:
        """Bytes that the toxic side saves over the ordinary one, by window: in the pair of segments, and in the trained pair."""
        toxic, ordinary, trained_toxic, trained_ordinary = self.compressors()
        cut = windows(text)
        return [len(ordinary(w)) - len(toxic(w)) for w in cut], [len(trained_ordinary(w)) - len(trained_toxic(w)) for w in cut]

    def features(self, text: str) -> tuple[float, ...]:
        """Of the segments: the largest distance, as a number and as steps, and how many windows stand out. Of the trained pair: the
        three largest distances, their mean, mean and spread of all, the number of windows, and how many stand out, as number and share."""
        d, other = self.distances(text) if text else ([], [])
        top = max(d, default=0)
        own = (min(top, 8) / 8, *(float(top >= k) for k in (2, 3, 4, 5)), float(np.log1p(sum(x >= 3 for x in d))), float(np.log1p(sum(x == 2 for x in d))))
        t = np.sort(np.array(other or [0], float))[::-1]
        first = [t[min(k, len(t) - 1)] / 8 for k in range(3)]
        steps = [*(float(np.log1p((t >= k).sum())) for k in (2, 4, 6, 8, 10)), *(float((t >= k).mean()) for k in (2, 4, 8))]
        return (*own, *map(float, first), float(t[:3].mean() / 8), float(t.mean()), float(t.std() / 4), float(np.log1p(len(t))), *steps)

    def score(self, text: str | None) -> float:
        if not self.weights or not text:
            return 0.0
        z = self.weights[0] + float(np.dot(self.weights[1:], self.features(text)))
        return float(1 / (1 + np.exp(-np.clip(z, -30, 30))))


def _logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float = 1.0) -> np.ndarray:
    w = np.zeros(x.shape[1])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = (x * (weight * p * (1 - p) + 1e-6)[:, None]).T @ x + ridge * np.eye(len(w))
        w = w + np.clip(np.linalg.solve(h, x.T @ (weight * (y - p)) - ridge * w), -2, 2)
    return w


def _dictionaries(toxic: list[str], ordinary: list[str]) -> Model:
    """Both pairs of dictionaries from these texts, without a curve."""
    grams = _grams(ordinary)
    counts = Counter(w for t in ordinary for w in set(re.findall(r"\w+", t.lower())))
    common = sorted(counts, key=lambda w: (-counts[w], w))[: BASE_BYTES // 7]  # ties by word: sets have no fixed order
    base = b" ".join(w.encode() for w in reversed(common))[-BASE_BYTES:]
    own = _typical(toxic, grams, len(ordinary), OWN_BYTES)
    # Zeros of the same length keep every offset into the base equal: neutral windows cost the same twice.
    return Model(own + base, bytes(len(own)) + base, [], _trained(toxic), _trained(ordinary))


def train(toxic: list[str], ordinary: list[str], ordinary_weight: float = 1.0) -> Model:
    """Curve and threshold from distances that each half of the texts has in dictionaries of the other half; the model's
    dictionaries then come from all texts.

    ``ordinary_weight``: how many ordinary documents of the corpus a sampled one stands for, in
    units of what a sampled toxic one stands for.
    """
    if not toxic or not ordinary:
        return Model()
    rows, y = [], []
    for k in (0, 1):
        model = _dictionaries(toxic[1 - k :: 2] or toxic, ordinary[1 - k :: 2] or ordinary)
        for label, texts in ((1.0, toxic[k::2]), (0.0, ordinary[k::2])):
            rows += [(1.0, *model.features(t)) for t in texts]
            y += [label] * len(texts)
    x, y = np.array(rows), np.array(y)
    # Features of one scale for the fit; the scale is taken out of the weights again.
    mean, spread = x[:, 1:].mean(0), x[:, 1:].std(0) + 1e-9
    x[:, 1:] = (x[:, 1:] - mean) / spread
    weight = np.where(y == 1, 1.0, ordinary_weight)
    w = _logistic(x, y, weight)
    z = np.sort(x @ w)
    cuts = np.concatenate([[z[0] - 1], (z[1:] + z[:-1]) / 2, [z[-1] + 1]])
    said = x @ w
    loss = np.array([(said[y == 1] < c).mean() + FALSE_COST * (said[y == 0] >= c).mean() for c in cuts])
    good = cuts[loss <= loss.min() + 1e-9]
    w[0] -= good[np.argmin(abs(good))]
    w[1:] /= spread
    w[0] -= w[1:] @ mean
    model = _dictionaries(toxic, ordinary)
    model.weights = w.tolist()
    return model


def fit(docs: DataFrame, labels: DataFrame, sample_docs: int = SAMPLE_DOCS, sample_chars: int = SAMPLE_CHARS) -> Model:
    """Train on at most ``sample_docs`` labelled documents of each class, taken in the order of a hash of their ids."""
    spark = docs.sparkSession
    order = F.xxhash64("doc_id")
    usable = labels.where("doc_id is not null and toxic in (0, 1)").where(fold() != HELD_OUT_FOLD)
    picked = None
    for y in (0, 1):
        one = usable.where(F.col("toxic") == y).select("doc_id", "toxic").distinct().orderBy(order, "doc_id").limit(sample_docs)
        picked = one if picked is None else picked.union(one)
    rows = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").where("text is not null")
    texts: dict[int, list[str]] = {0: [], 1: []}
    held = {0: 0, 1: 0}
    for r in rows.select("doc_id", "toxic", F.col("text").alias("t")).orderBy(order, "doc_id", "t").toLocalIterator():
        if held[r["toxic"]] < sample_chars:
            texts[r["toxic"]].append(r["t"])
            held[r["toxic"]] += len(r["t"])
        elif min(held.values()) >= sample_chars:
            break
    n = {r["toxic"]: r["count"] for r in usable.groupBy("toxic").count().collect()}
    if not texts[1] or not texts[0]:
        return Model()
    return train(texts[1], texts[0], (n[0] / len(texts[0])) / (n[1] / len(texts[1])))


def score(docs: DataFrame, model: Model, text: str = "text") -> DataFrame:
    """``docs`` with ``score``."""
    state = docs.sparkSession.sparkContext.broadcast(pickle.dumps(model))  # some hundreds of KB
    keep = [c for c in docs.columns if c != "score"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = pickle.loads(state.value)
        for whole in batches:
            for i in range(0, whole.num_rows, SLICE_ROWS):
                part = whole.slice(i, SLICE_ROWS)
                scores = [own.score(t) for t in part.column(text).to_pylist()]
                yield pa.RecordBatch.from_arrays([*(part.column(c) for c in keep), pa.array(scores, pa.float64())], names=[*keep, "score"])

    return docs.select(*keep).mapInArrow(run, docs.select(*keep, F.lit(0.0).alias("score")).schema)


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    model = fit(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    scored = score(docs, model).drop("text")
    return scored.select("doc_id", (fold() == HELD_OUT_FOLD).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
