"""Toxic passages by maximum-scoring segments over token log-odds.

Words are runs of letters (ASCII letters in lower case, and all bytes above 127). A token is
a whole word or one of its leading parts (PREFIXES, in bytes), which stand in for inflected
and compound forms. Log-odds of tokens between toxic and clean labelled rows, counted at
most CAP times a row, carry a Dirichlet prior of half a count and PRIOR counts in proportion
to the tokens' shares in both together, and are shrunk towards zero by their own evidence
(by z**4 / (z**4 + HALF_Z**4) of their z-values z). Every word scores the log-odds, of either sign, of its
strongest token seen MIN_COUNT times (the longest of equals), and zero without one; all words
pay a toll such that clean text loses DRIFT a word on average. A linear-time scan then lists all
maximal segments of a text with a positive score, its passages.

With a negative drift the best segment of clean texts follows an extreme-value law whose place
grows with the log of the length; its place and width are fitted by moments on clean rows. The score is a logistic fit on the best segment's reduced value and the sum
of significant segments. Counts come from folds 2 to 4, the calibration from fold 1; fold 0
is never learned from. LABEL_ROWS bounds the labelled rows used, and so the model.

Defined results: null and empty texts have no segment and get the score of none; without
labelled rows of both classes the score is 0; ties between segments go to the earlier one;
repeated rows get equal scores; an empty table gives an empty result. Labels, lang, source
and doc_id are no inputs of a score; extra columns aren't read.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import Block, blocks, frugal, mix
from .labelled import fit_logistic, labelled_texts, sigmoid

U64 = np.uint64
LABEL_ROWS = 20_000
MIN_COUNT = 3
CAP = 4
PREFIXES = (4, 6, 8)
PRIOR = 500.0
HALF_Z = 4.0
DRIFT = 0.05
#: Chance at which a segment of a clean text counts as significant.
ALPHA = 0.01

_NOT_LETTER = np.ones(256, dtype=bool)
_NOT_LETTER[[*range(ord("a"), ord("z") + 1), *range(ord("A"), ord("Z") + 1), *range(128, 256)]] = False


def maximal_segments(firsts: list[int], lasts: list[int], before: list[float], through: list[float]) -> list[tuple[int, int, float]]:
    """All maximal segments (first and last place, score) of a sequence in linear time.

    Its runs of positive scores are given: their first and last places, and the sums of all
    scores before and through each.
    """
    # Each open candidate: first place, last place, total before it, total through it, index of the nearest candidate left of it with a smaller total before it.
    first, last, under, top, smaller = [], [], [], [], []
    for a, z, low, high in zip(firsts, lasts, before, through, strict=True):
        while True:
            j = len(first) - 1
            while j >= 0 and under[j] >= low:
                j = smaller[j]
            if j < 0 or top[j] >= high:
                break
            a, low = first[j], under[j]
            for stack in (first, last, under, top, smaller):
                del stack[j:]
        first.append(a)
        last.append(z)
        under.append(low)
        top.append(high)
        smaller.append(j)
    return [(a, z, t - l) for a, z, l, t in zip(first, last, under, top, strict=True)]


class HashTable:
    """Open addressing from 64-bit hashes to scores."""

    def __init__(self, keys: np.ndarray, values: np.ndarray) -> None:
        self.mask = (1 << max(4, int(3 * len(keys)).bit_length())) - 1
        self.keys, self.values = np.zeros(self.mask + 1, dtype=U64), np.zeros(self.mask + 1, dtype=np.float32)
        self.taken = np.zeros(self.mask + 1, dtype=bool)
        at, todo = self._home(keys), np.arange(len(keys))
        while len(todo):
            free = todo[~self.taken[at[todo]]]
            _, one = np.unique(at[free], return_index=True)
            won = free[one]
            self.keys[at[won]], self.values[at[won]], self.taken[at[won]] = keys[won], values[won], True
            left = np.ones(len(keys), dtype=bool)
            left[won] = False
            todo = todo[left[todo]]
            at[todo] = at[todo] + 1 & self.mask

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return (keys >> U64(20)).astype(np.int64) & self.mask

    def get(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which keys are there (their indices), and their scores."""
        at, todo, rows, found = self._home(keys), np.arange(len(keys)), [], []
        while len(todo):
            spot = at[todo]
            hit = self.taken[spot] & (self.keys[spot] == keys[todo])
            rows.append(todo[hit])
            found.append(self.values[spot[hit]])
            todo = todo[self.taken[spot] & ~hit]
            at[todo] = at[todo] + 1 & self.mask
        return (np.concatenate(rows), np.concatenate(found)) if rows else (np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.float32))


@dataclass(frozen=True)
class ToxicModel:
    tokens: HashTable | None = None
    toll: float = 0.0
    centre: float = 0.0
    width: float = 1.0
    fit: np.ndarray | None = None

    def word_scores(self, block: Block) -> tuple[np.ndarray, tuple]:
        """The log-odds of every word of a block, and the words' spans."""
        starts, ends, firsts = spans = block.spans(_NOT_LETTER)
        score = np.zeros(len(starts))
        for hashes, of in _tokens(block, starts, ends) if self.tokens is not None else ():
            at, found = self.tokens.get(hashes)
            place = of[at]
            score[place] = np.where(np.abs(found) >= np.abs(score[place]), found, score[place])
        return score, spans

    def segments(self, block: Block) -> tuple[list[list[tuple[int, int, float]]], np.ndarray, tuple]:
        score, spans = self.word_scores(block)
        firsts = spans[2]
        score -= self.toll
        out: list[list[tuple[int, int, float]]] = [[] for _ in range(block.n)]
        total = np.concatenate([[0.0], np.cumsum(score)])
        up = score > 0
        edge = np.zeros(len(score), dtype=bool)
        edge[firsts[:-1][np.diff(firsts) > 0]] = True
        begin, finish = up.copy(), up.copy()
        begin[1:] &= ~up[:-1] | edge[1:]
        finish[:-1] &= ~up[1:] | edge[1:]
        begin, finish = np.flatnonzero(begin), np.flatnonzero(finish)
        lo = np.searchsorted(begin, firsts).tolist()
        before, through = total[begin].tolist(), total[finish + 1].tolist()
        for i in np.flatnonzero(np.diff(lo)).tolist():
            a, b = lo[i], lo[i + 1]
            out[i] = maximal_segments((begin[a:b] - firsts[i]).tolist(), (finish[a:b] - firsts[i]).tolist(), before[a:b], through[a:b])
        return out, np.diff(firsts), spans

    def limit(self, n_words: int) -> float:
        """The score that a clean text of so many words exceeds with the chance ALPHA."""
        return self.centre + float(np.log(max(n_words, 1))) - self.width * float(np.log(-np.log1p(-ALPHA)))

    def features(self, found: list, n_words: int) -> tuple[float, ...]:
        """The best segment's reduced value, and the log of the significant segments' sum."""
        best = max((s for *_, s in found), default=0.0)
        reduced = (best - self.centre - float(np.log(max(n_words, 1)))) / self.width if found else -8.0
        strong = sum(s for *_, s in found if s >= self.limit(n_words))
        return float(np.clip(reduced, -8, 30)), float(np.log1p(strong))

    def score(self, features: np.ndarray) -> np.ndarray:
        if self.fit is None:
            return np.zeros(len(features))
        return sigmoid(features @ self.fit[:-1] + self.fit[-1])


def _tokens(block: Block, starts: np.ndarray, ends: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Hashes of tokens and their words' numbers, from the shortest tokens to whole words."""
    for width in PREFIXES:
        of = np.flatnonzero(ends - starts > width)
        yield block.span_hashes(starts[of], starts[of] + width, lower=True), of
    yield block.span_hashes(starts, ends, lower=True), np.arange(len(starts))


def _class_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        label = batch.column("label").to_numpy()
        for block in blocks(batch.column("text")):
            starts, ends, firsts = block.spans(_NOT_LETTER)
            row = np.repeat(np.arange(block.n), np.diff(firsts))
            parts = list(_tokens(block, starts, ends))
            words, rows = np.concatenate([h for h, _ in parts]), row[np.concatenate([of for _, of in parts])]
            _, one, times = np.unique(mix(words ^ mix(rows.astype(U64))), return_index=True, return_counts=True)
            words, toxic, times = words[one], label[block.first + rows[one]] == 1, np.minimum(times, CAP)
            every, at = np.unique(words, return_inverse=True)
            n = np.bincount(at, times, minlength=len(every)).astype(np.int64)
            t = np.bincount(at[toxic], times[toxic], minlength=len(every)).astype(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(every.view(np.int64)), pa.array(t), pa.array(n - t)], names=["word", "n_toxic", "n_clean"])


def word_odds(texts: DataFrame) -> DataFrame:
    """word (hash), its counts and its shrunken log-odds, for labelled texts."""
    counts = texts.mapInArrow(frugal(_class_counts), "word long, n_toxic long, n_clean long").groupBy("word").agg(F.sum("n_toxic").alias("t"), F.sum("n_clean").alias("c"))
    sums = counts.agg(F.sum("t").alias("all_t"), F.sum("c").alias("all_c")).first()
    all_t, all_c = float(sums["all_t"] or 0), float(sums["all_c"] or 0)
    prior = F.lit(0.5) + F.lit(PRIOR) * (F.col("t") + F.col("c")) / F.lit(max(1.0, all_t + all_c))
    t, c = F.col("t") + prior, F.col("c") + prior
    odds = F.log(t / (F.lit(all_t + PRIOR) - t)) - F.log(c / (F.lit(all_c + PRIOR) - c))
    square = odds * odds / (1 / t + 1 / c) / F.lit(HALF_Z**2)  # of the z-value, in units of HALF_Z
    shrink = square * square / (square * square + 1)
    return counts.where(F.col("t") + F.col("c") >= MIN_COUNT).select("word", "t", "c", (odds * shrink).alias("odds"))


def _clean_mean(texts: DataFrame, model: ToxicModel) -> float:
    """The mean score of a word of clean rows."""
    sent = texts.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for block in blocks(batch.column("text")):
                score, _ = sent.value.word_scores(block)
                yield pa.RecordBatch.from_pydict({"total": [float(score.sum())], "n": [len(score)]})

    got = texts.where("label = 0").mapInArrow(frugal(run), "total double, n long").agg(F.sum("total"), F.sum("n")).first()
    return (got[0] or 0.0) / max(1, got[1] or 0)


def fit_toxicity(docs: DataFrame, labels: DataFrame, rows: int = LABEL_ROWS) -> ToxicModel:
    texts = labelled_texts(docs, labels, "toxic", rows)
    learn = texts.where("fold > 1")
    # The sample bounds the tokens, which the driver turns into one table.
    odds = word_odds(learn).select("word", "odds").toPandas()
    if not len(odds) or texts.select("label").distinct().count() < 2:
        return ToxicModel()
    bare = ToxicModel(HashTable(odds["word"].to_numpy(dtype=np.int64).view(U64), odds["odds"].to_numpy(dtype=np.float32)))
    bare = replace(bare, toll=max(0.0, _clean_mean(learn, bare) + DRIFT))
    sent = docs.sparkSession.sparkContext.broadcast(bare)

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows, sizes = [], []
            for block in blocks(batch.column("text")):
                found, n, _ = sent.value.segments(block)
                rows += [[s for *_, s in x] for x in found]
                sizes += n.tolist()
            yield pa.RecordBatch.from_arrays([batch.column("label"), batch.column("fold"), pa.array(sizes, type=pa.int64()), pa.array(rows, type=pa.list_(pa.float64()))], names=["label", "fold", "n", "scores"])

    got = texts.mapInArrow(frugal(best), "label int, fold int, n long, scores array<double>").toPandas()
    clean = got[(got["label"] == 0) & (got["scores"].map(len) > 0)]
    reduced = np.array([max(s) - np.log(max(n, 1)) for s, n in zip(clean["scores"], clean["n"], strict=True)])
    width = max(0.25, float(reduced.std() * np.sqrt(6) / np.pi)) if len(reduced) > 10 else 1.0
    centre = float(reduced.mean() - 0.5772156649 * width) if len(reduced) > 10 else -float(np.log(100.0))
    ready = replace(bare, centre=centre, width=width)
    apart = got[got["fold"] == 1]
    if min((apart["label"] == 1).sum(), (apart["label"] == 0).sum()) < 20:  # too few to fit on alone
        apart = got
    if apart["label"].nunique() < 2:
        return ready
    x = np.array([ready.features([(0, 0, s) for s in scores], n) for scores, n in zip(apart["scores"], apart["n"], strict=True)])
    return replace(ready, fit=fit_logistic(x, apart["label"].to_numpy(dtype=float), ridge=0.05))


PASSAGES = "array<struct<start: long, end: long, score: double>>"


def score_toxicity(docs: DataFrame, model: ToxicModel, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, score, best segment and significant passages (code points, end exclusive) of every text."""
    sent = docs.sparkSession.sparkContext.broadcast(model)
    passage = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        toxic = sent.value
        for batch in batches:
            features, bests, passages = [], [], []
            for block in blocks(batch.column("text")):
                found, n, (starts, ends, firsts) = toxic.segments(block)
                for i, own in enumerate(found):
                    features.append(toxic.features(own, int(n[i])))
                    bests.append(max((s for *_, s in own), default=0.0))
                    lead, strong = None, []
                    for a, b, s in own:
                        if s >= toxic.limit(int(n[i])):
                            lead = np.concatenate([[0], np.cumsum((block.data[block.bounds[i] : block.bounds[i + 1]] & 0xC0) != 0x80)]) if lead is None else lead
                            at, to = starts[firsts[i] + a] - block.bounds[i], ends[firsts[i] + b] - block.bounds[i]
                            strong.append({"start": int(lead[at]), "end": int(lead[to]), "score": s})
                    passages.append(strong)
            scores = toxic.score(np.array(features, dtype=float).reshape(-1, 2))
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array(scores, type=pa.float64()), pa.array(bests, type=pa.float64()), pa.array(passages, type=passage)], names=[key, "score", "best", "passages"])

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("key"), F.col(text).alias("text")).mapInArrow(frugal(run), f"`{key}` {kind}, score double, best double, passages {PASSAGES}")


def drop_toxic(docs: DataFrame, model: ToxicModel, text: str = "text", reject_at: float = 0.5) -> DataFrame:
    """docs without the rows whose score reaches reject_at; rows aren't joined but judged where they are."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        toxic = sent.value
        for batch in batches:
            features = []
            for block in blocks(batch.column(text)):
                found, n, _ = toxic.segments(block)
                features += [toxic.features(own, int(k)) for own, k in zip(found, n, strict=True)]
            scores = toxic.score(np.array(features, dtype=float).reshape(-1, 2))
            yield batch.filter(pa.array(scores < reject_at))

    return docs.mapInArrow(frugal(run), docs.schema)
