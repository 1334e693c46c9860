"""Quality rules: exact base counts, and a hashed n-gram logistic regression with calibration.

Features of the regression are hashed counts of lower-cased words and word pairs and of
character n-grams (runs of 3 and 4 UTF-8 bytes), divided by their number in the text. It is
fitted on a bounded sample of labelled rows (LABEL_ROWS) of folds 2 to 4, calibrated by a
logistic fit on fold 1, and applied in Arrow batches. A text is kept unless it fails a base
rule or its probability of good quality is below KEEP_AT.

Defined results: null and empty texts have no words and so fail the base rules; without
labelled rows of both classes every probability is 0.5 (and passes); repeated rows get
equal results; an empty table gives an empty result; extra columns aren't read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import IS_SPACE, Block, blocks, frugal, mix, windows
from .labelled import fit_logistic, labelled_texts, sigmoid

U64 = np.uint64
LABEL_ROWS = 4000
BITS = 17
SCALE = 40.0
KEEP_AT = 0.4
MIN_WORDS, REPEAT_PERCENT, WINDOW = 10, 20, 5
SYMBOLS = b"#*$%&|<>"

_IS_SYMBOL = np.zeros(256, dtype=bool)
_IS_SYMBOL[list(SYMBOLS)] = True
_NOT_NEWLINE = np.zeros(256, dtype=bool)
_NOT_NEWLINE[10] = True


def _sums(flags: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0], np.cumsum(flags, dtype=np.int64)])
    return total[bounds[1:]] - total[bounds[:-1]]


def base_counts(block: Block) -> dict[str, np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines and n_repeat_words of each text of a block."""
    data, bounds, n = block.data, block.bounds, block.n
    starts, ends, firsts = block.spans()
    word = ~IS_SPACE[data]
    out = {"n_words": np.diff(firsts), "word_chars": _sums(word & ((data & 0xC0) != 0x80), bounds), "n_symbols": _sums(_IS_SYMBOL[data], bounds)}

    lo, hi, of = block.spans(_NOT_NEWLINE)
    seen = np.concatenate([[0], np.cumsum(word, dtype=np.int64)])
    filled = seen[hi] > seen[lo]
    owner = np.repeat(np.arange(n), np.diff(of))[filled]
    keys = mix(block.span_hashes(lo[filled], hi[filled]) ^ owner.astype(U64) * U64(0x9E3779B97F4A7C15))
    _, first = np.unique(keys, return_index=True)
    out["n_dup_lines"] = np.bincount(owner, minlength=n) - np.bincount(owner[first], minlength=n)

    runs, run_bounds = windows(block.span_hashes(starts, ends), firsts, WINDOW)
    owner = np.repeat(np.arange(n), np.diff(run_bounds))
    keys = mix(runs ^ owner.astype(U64) * U64(0x9E3779B97F4A7C15))
    order = np.argsort(keys)
    same = keys[order][1:] == keys[order][:-1]
    twice = np.zeros(len(keys), dtype=bool)
    twice[order[1:][same]] = twice[order[:-1][same]] = True
    at = firsts[owner[twice]] + np.flatnonzero(twice) - run_bounds[owner[twice]]
    edge = np.bincount(at, minlength=len(starts) + WINDOW + 1) - np.bincount(at + WINDOW, minlength=len(starts) + WINDOW + 1)
    out["n_repeat_words"] = _sums((np.cumsum(edge) > 0)[: len(starts)], firsts)
    return out


def _buckets(block: Block) -> list[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(bucket of each feature, first and last feature of each text) for each kind of feature."""
    shift, out = U64(64 - BITS), []
    starts, ends, firsts = block.spans()
    words = block.span_hashes(starts, ends, lower=True)
    out.append(((words >> shift).astype(np.int64), firsts[:-1], firsts[1:]))
    pairs, bounds = windows(words, firsts, 2)
    out.append(((pairs >> shift).astype(np.int64), bounds[:-1], bounds[1:]))
    data = block.data.astype(U64)
    for width in (3, 4):
        if len(data) < width:
            out.append((np.zeros(0, dtype=np.int64), block.bounds[:-1] * 0, block.bounds[:-1] * 0))
            continue
        packed = np.full(len(data) - width + 1, width, dtype=U64)
        for k in range(width):
            packed = packed << U64(8) | data[k : len(data) - width + 1 + k]
        lo = np.minimum(block.bounds[:-1], len(packed))
        out.append(((packed * U64(0x9E3779B97F4A7C15) >> shift).astype(np.int64), lo, np.maximum(lo, np.minimum(block.bounds[1:] - width + 1, len(packed)))))
    return out


@dataclass(frozen=True)
class QualityModel:
    """Weights by bucket, their bias, and slope and offset of the calibration."""

    weights: np.ndarray
    bias: float
    slope: float
    offset: float

    def scores(self, block: Block) -> np.ndarray:
        total, n = np.zeros(block.n), np.zeros(block.n)
        for bucket, lo, hi in _buckets(block):
            sums = np.concatenate([[0.0], np.cumsum(self.weights[bucket], dtype=np.float64)])
            total += sums[hi] - sums[lo]
            n += hi - lo
        return self.bias + SCALE * total / np.maximum(n, 1)

    def probabilities(self, block: Block) -> np.ndarray:
        return sigmoid(self.slope * self.scores(block) + self.offset)


def _sparse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Feature buckets and their shares of each labelled text, as packed int32 and float32."""
    for batch in batches:
        places, shares = [], []
        for block in blocks(batch.column("text")):
            kinds = _buckets(block)
            for i in range(block.n):
                every = np.concatenate([b[lo[i] : hi[i]] for b, lo, hi in kinds])
                place, count = np.unique(every, return_counts=True)
                places.append(place.astype("<i4").tobytes())
                shares.append((count / max(1, len(every))).astype("<f4").tobytes())
        yield pa.RecordBatch.from_arrays([batch.column("label"), batch.column("fold"), pa.array(places, type=pa.binary()), pa.array(shares, type=pa.binary())], names=["label", "fold", "place", "share"])


def train_sparse(places: list[np.ndarray], shares: list[np.ndarray], labels: np.ndarray, steps: int = 120, rate: float = 0.1, ridge: float = 1e-4) -> tuple[np.ndarray, float]:
    """Full-batch Adam on the log loss of sparse rows, with both classes weighted alike."""
    counts = np.array([len(p) for p in places])
    row = np.repeat(np.arange(len(places)), counts)
    place, share = np.concatenate(places), np.concatenate(shares) * SCALE
    balance = np.where(labels == 1, 0.5 / max(1, labels.sum()), 0.5 / max(1, (1 - labels).sum()))
    size = 1 << BITS
    w, bias = np.zeros(size), 0.0
    m, v, mb, vb = np.zeros(size), np.zeros(size), 0.0, 0.0
    for t in range(1, steps + 1):
        p = sigmoid(np.bincount(row, w[place] * share, minlength=len(places)) + bias)
        error = (p - labels) * balance
        g, gb = np.bincount(place, share * error[row], minlength=size) + ridge * w, error.sum()
        m, v, mb, vb = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g, 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb * gb
        up, down = 1 - 0.9**t, 1 - 0.99**t
        w -= rate * (m / up) / (np.sqrt(v / down) + 1e-6)
        bias -= rate * (mb / up) / (np.sqrt(vb / down) + 1e-6)
    return w, bias


def fit_quality(docs: DataFrame, labels: DataFrame, rows: int = LABEL_ROWS) -> QualityModel:
    """Fit on at most about ``rows`` labelled rows; the driver gets their bucket shares, not their texts."""
    got = labelled_texts(docs, labels, "quality", rows).mapInArrow(frugal(_sparse), "label int, fold int, place binary, share binary").toArrow().to_pydict()
    label, fold = np.array(got["label"], dtype=np.int64), np.array(got["fold"], dtype=np.int64)
    place = [np.frombuffer(x, "<i4") for x in got["place"]]
    share = [np.frombuffer(x, "<f4") for x in got["share"]]
    learn, calibrate = np.flatnonzero(fold > 1), np.flatnonzero(fold == 1)
    if len(set(label[learn].tolist())) < 2:
        return QualityModel(np.zeros(1 << BITS, dtype=np.float32), 0.0, 0.0, 0.0)
    w, bias = train_sparse([place[i] for i in learn], [share[i] for i in learn], label[learn])
    slope, offset = 1.0, 0.0
    if len(set(label[calibrate].tolist())) == 2:
        raw = np.array([bias + SCALE * float(w[place[i]] @ share[i]) for i in calibrate])
        slope, offset = fit_logistic(raw[:, None], label[calibrate])
    return QualityModel(w.astype(np.float32), float(bias), float(slope), float(offset))


COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def judge_quality(docs: DataFrame, model: QualityModel, key: str = "doc_id", text: str = "text", keep_at: float = KEEP_AT) -> DataFrame:
    """key, the counts, base_failed, kept and the calibrated probability of every text."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            parts = [(base_counts(b), sent.value.probabilities(b)) for b in blocks(batch.column("text"))]
            if not parts:
                continue
            n = {k: np.concatenate([x[k] for x, _ in parts]).astype(np.int64) for k in COUNTS}
            p = np.concatenate([x for _, x in parts])
            failed = (n["n_words"] < MIN_WORDS) | (100 * n["n_repeat_words"] > REPEAT_PERCENT * n["n_words"])
            columns = [batch.column("key"), *[pa.array(n[k]) for k in COUNTS], pa.array(failed), pa.array(~failed & (p >= keep_at)), pa.array(p)]
            yield pa.RecordBatch.from_arrays(columns, names=[key, *COUNTS, "base_failed", "kept", "probability"])

    kind = docs.schema[key].dataType.simpleString()
    spec = f"`{key}` {kind}, " + ", ".join(f"{k} long" for k in COUNTS) + ", base_failed boolean, kept boolean, probability double"
    return docs.select(F.col(key).alias("key"), F.col(text).alias("text")).mapInArrow(frugal(run), spec)
