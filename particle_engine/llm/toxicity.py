"""Toxicity by compression distance: two zstandard dictionaries and calibrated thresholds.

Learning takes a bounded, documented sample of labelled rows: the first ``SAMPLE`` in
hash order, as many of them as hold ``SAMPLE_BYTES`` together.  zstandard's trainer builds one
dictionary from toxic and one from ordinary texts.  It is given, of each text, the words
that set its class apart: those made of ``GRAM``-byte strings found in more texts of the class than of
the other, by ``Z_TOXIC`` or ``Z_ORDINARY`` standard errors (language that both share would only
add noise to the difference of two lengths).  A class without such words is trained on whole windows
of its texts, so neither dictionary is ever empty.

A text is cut into windows; a window's distance is its compressed length with the ordinary
dictionary less that with the toxic one.  Counts and shares of windows over each of
``THRESHOLDS``, the largest and the mean distance go into a logistic calibration
fitted on the sample.

Defined results: null text counts as empty; empty texts score the calibration's
value for no distance; a sample of one class only scores every text by that
class's rate; of rows that repeat a labelled doc_id the smallest text is learnt from, and a doc_id
labelled both ways counts as toxic; repeated rows score alike.  Only the text enters a score.
"""

from __future__ import annotations

import math
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard as zs
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from particle_engine.llm.common import small_batches

SAMPLE, SAMPLE_BYTES = 6000, 64 << 20
WINDOW, OVERLAP = 32, 12
GRAM, Z_TOXIC, Z_ORDINARY = 5, 4.5, 2.0
MOST_WORDS, ORDINARY_WORDS = 300, 20
TOXIC_BYTES, ORDINARY_BYTES = 1024, 256
FOLDS = 5
THRESHOLDS = (2, 3, 4, 5, 6, 8)
NOT_WORD = re.compile(rb"[\x00-\x40\x5b-\x60\x7b-\x7f]+")


def _plain(text: str | None) -> bytes:
    """Lower case, with one space for every run of other ASCII characters than letters."""
    return NOT_WORD.sub(b" ", b" " + (text or "").lower().encode("utf-8", "surrogatepass") + b" ")


def _grams(data: bytes) -> np.ndarray:
    """The ``GRAM``-byte strings at every place, as integers."""
    a = np.frombuffer(data, np.uint8).astype(np.uint64)
    out = np.zeros(max(0, len(a) - GRAM + 1), np.uint64)
    for i in range(GRAM):
        out = (out << np.uint64(8)) | a[i : i + len(out)]
    return out


def _frequencies(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct strings of a class and the number of texts that have each."""
    return np.unique(np.concatenate([np.unique(_grams(t)) for t in texts]), return_counts=True)


def _z(a: np.ndarray, b: np.ndarray, n1: int, n0: int) -> np.ndarray:
    """Standard errors between the document frequencies a of n1 and b of n0."""
    p = (a + b) / (n1 + n0)
    return (a / n1 - b / n0) / np.sqrt(p * (1 - p) * (1 / n1 + 1 / n0) + 1e-12)


def _runs(text: bytes, grams: np.ndarray) -> list[bytes]:
    """The parts of a text that strings of ``grams`` cover."""
    hit = np.isin(_grams(text), grams)
    covered = np.zeros(len(text) + 2, np.int8)
    for i in range(GRAM):
        covered[1 + i : 1 + i + len(hit)] |= hit
    edges = np.flatnonzero(np.diff(covered))
    return [text[i:j] for i, j in zip(edges[::2].tolist(), edges[1::2].tolist())]


def distinctive(own: list[bytes], other: list[bytes], least: float, most: int = MOST_WORDS) -> list[bytes]:
    """Words and beginnings of words that set one class's texts apart by ``least`` standard errors, most distinctive first."""
    n1, n0 = len(own), len(other)
    (grams, a), (others, c) = _frequencies(own), _frequencies(other)
    at = np.minimum(np.searchsorted(others, grams), max(0, len(others) - 1))
    b = np.where(others[at] == grams, c[at], 0) if len(others) else np.zeros(len(grams))
    grams = grams[(a >= max(5, n1 // 100)) & (_z(a, b, n1, n0) >= least)]
    if not len(grams):
        return []
    words: Counter = Counter()
    for t in own:
        words.update({b" " + w for run in _runs(t, grams) for w in run.split(b" ") if len(w) >= 4})
    z_of = lambda word: float(_z(np.float64(sum(word in t for t in own)), np.float64(sum(word in t for t in other)), n1, n0))
    scored = []
    for word, n in sorted(words.items(), key=lambda x: (-x[1], x[0]))[:most]:
        if n >= 5 and (z := z_of(word)) >= least:
            closed = z_of(word + b" ")  # a whole word is told from words it begins
            scored.append((closed, word + b" ") if closed >= 0.9 * z else (z, word))
    best: list[bytes] = []
    for _, word in sorted(scored, reverse=True):
        if not any(word in b for b in best):
            best.append(word)
    return best


def trained(words: list[bytes], texts: list[bytes], size: int) -> bytes:
    """A dictionary zstandard trains on what the texts have of ``words``; without words on the texts' windows."""
    samples = [t[i : i + 256] for t in texts for i in range(0, len(t), 256)][: 1 << 16]
    if words:
        any_word = re.compile(b"|".join(re.escape(w) for w in sorted(words, key=len, reverse=True)))
        samples = [b"".join(found) for t in texts if (found := any_word.findall(t.replace(b" ", b"  ")))]
    try:
        return zs.train_dictionary(size, samples, k=16, d=8).as_bytes()
    except zs.ZstdError:  # the trainer wants more samples than there are: they are the dictionary
        return b"".join(dict.fromkeys(samples))[-size:]


@dataclass
class Model:
    """All a worker needs: two dictionaries, the primer, and the calibration."""

    toxic: bytes = b""
    ordinary: bytes = b""
    primer: bytes = b""
    mean: np.ndarray | None = None
    scale: np.ndarray | None = None
    weights: np.ndarray | None = None
    rate: float = 0.0

    def __post_init__(self) -> None:
        self._pair = None

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "_pair"} | {"_pair": None}

    def distances(self, text: str | None) -> np.ndarray:
        if self._pair is None:
            # the fast strategy leaves literals as they are, so lengths differ by matches alone
            settings = zs.ZstdCompressionParameters(window_log=12, hash_log=14, chain_log=12, search_log=1, min_match=5, target_length=1, strategy=zs.STRATEGY_FAST, write_content_size=False, write_checksum=False, write_dict_id=False)
            self._pair = [zs.ZstdCompressor(dict_data=zs.ZstdCompressionDict(d, dict_type=zs.DICT_TYPE_RAWCONTENT), compression_params=settings).compress for d in (self.ordinary, self.toxic)]
        plain, toxic = self._pair
        data, primer = _plain(text), self.primer
        windows = [primer + data[i : i + WINDOW + OVERLAP] for i in range(0, max(1, len(data) - OVERLAP), WINDOW)]
        return np.array([len(plain(w)) - len(toxic(w)) for w in windows])

    def features(self, text: str | None) -> np.ndarray:
        d = self.distances(text)
        over = [np.count_nonzero(d >= t) for t in THRESHOLDS]
        n = len(d)
        return np.array([min(d.max(), 12), d.mean(), math.log(n), *(math.log1p(o) for o in over), *(o / math.sqrt(n) for o in over), *(o / n for o in over)])

    def score(self, text: str | None) -> float:
        if self.weights is None:
            return self.rate
        x = np.r_[1.0, (self.features(text) - self.mean) / self.scale]
        return float(1 / (1 + math.exp(-float(np.clip(x @ self.weights, -30, 30)))))


def fit(texts: list[str | None], labels: list[int]) -> Model:
    toxic = [_plain(t) for t, y in zip(texts, labels) if y]
    ordinary = [_plain(t) for t, y in zip(texts, labels) if not y]
    model = Model(rate=(len(toxic) / len(texts) if texts else 0.0))
    if not toxic or not ordinary:
        return model
    rng = np.random.default_rng(0)
    # the primer ends both dictionaries and begins every window, so no window is stored uncompressed
    model.primer = bytes(rng.integers(128, 255, 48, dtype=np.uint8))
    pair = [
        trained(distinctive(toxic, ordinary, Z_TOXIC), toxic, TOXIC_BYTES),
        trained(distinctive(ordinary, toxic, Z_ORDINARY, 3 * ORDINARY_WORDS)[:ORDINARY_WORDS], ordinary, ORDINARY_BYTES),
    ]
    neutral = bytes(rng.integers(128, 255, TOXIC_BYTES, dtype=np.uint8))
    model.toxic, model.ordinary = (neutral[: max(map(len, pair)) - len(p)] + p + model.primer for p in pair)
    x = np.array([model.features(t) for t in texts])
    model.mean, model.scale = x.mean(0), x.std(0) + 1e-6
    x = np.c_[np.ones(len(x)), (x - model.mean) / model.scale]
    y, w = np.array(labels, float), np.zeros(x.shape[1])
    penalty = np.diag(np.r_[1e-6, np.full(x.shape[1] - 1, 0.3)])
    for _ in range(30):  # Newton steps of a ridge logistic fit
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p) + 1e-9)[:, None]).T @ x + penalty, x.T @ (y - p) - penalty @ w)
        w += step
        if np.abs(step).max() < 1e-6:
            break
    model.weights = w
    return model


def held_out(doc_id: str) -> Column:
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(FOLDS)) == 0


def train(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, sample_bytes: int = SAMPLE_BYTES) -> Model:
    """Fit on at most ``sample`` labelled rows outside the held-out fold, smallest hashes first, while they fit in ``sample_bytes``."""
    known = labels.where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), (F.col("toxic") != 0).cast("int").alias("y")).where(~held_out("doc_id"))
    known = known.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).join(F.broadcast(known), "doc_id")
    sizes = texts.groupBy("doc_id").agg(F.max(F.octet_length("text")).alias("size")).collect()  # at most ``sample`` rows of two numbers
    order = np.argsort([zlib.crc32(str(r["doc_id"]).encode()) for r in sizes], kind="stable")
    taken = np.cumsum([sizes[i]["size"] for i in order]) <= sample_bytes
    ids = [sizes[i]["doc_id"] for i, fits in zip(order, taken) if fits]
    if not ids:
        return fit([], [])
    chosen = F.broadcast(docs.sparkSession.createDataFrame([(i,) for i in ids], "doc_id long"))
    rows = texts.join(chosen, "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.max("y").alias("y")).orderBy("doc_id").collect()
    return fit([r["text"] for r in rows], [r["y"] for r in rows])


def score_documents(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """(doc_id, held_out, score, predicted): one row per document."""
    model = docs.sparkSession.sparkContext.broadcast(train(docs, labels, sample))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = pa.array([model.value.score(t.as_py()) for t in batch.column(2)], pa.float64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), score], ["doc_id", "held_out", "score"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(held_out("doc_id"), F.lit(False)).alias("held_out"), F.col("text").cast("string").alias("text"))
    scored = small_batches(rows).mapInArrow(run, "doc_id long, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def reject_toxic(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """Rows of ``docs`` (all columns) whose score is under 0.5."""
    model = docs.sparkSession.sparkContext.broadcast(train(docs, labels, sample))

    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array([model.value.score(t.as_py()) < 0.5 for t in batch.column(at)], pa.bool_()))

    rows = small_batches(docs.withColumn("text", F.col("text").cast("string")))
    return rows.mapInArrow(run, rows.schema)


def crc_fold(doc_id: int) -> int:
    return zlib.crc32(str(doc_id).encode()) % FOLDS
