"""Quality and toxicity rules against plain versions and held-out labels."""

import itertools
import math
import random
import re
import zlib

import numpy as np
import pyarrow as pa

from linkfactor.llm import kernels, quality, toxicity
from linkfactor.llm.cluster import table
from linkfactor.llm.queries_rules import op3_quality, op9_toxicity

SMALL, MID = "/root/testdata/sf0.001", "/root/testdata/sf0.01"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def plain_counts(text):
    words = WORD.findall(text or "")
    seen, dup = set(), 0
    for line in (text or "").split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    runs = {}
    for i in range(len(words) - 4):
        runs.setdefault(tuple(words[i : i + 5]), []).append(i)
    covered = {k for at in runs.values() if len(at) > 1 for i in at for k in range(i, i + 5)}
    return len(words), sum(map(len, words)), sum((text or "").count(c) for c in "#*$%&|<>"), dup, len(covered)


def test_op3_base_counts_and_held_out_quality(spark):
    docs = {r.doc_id: r.text for r in table(spark, MID, "documents").collect()}
    rows = op3_quality(spark, MID).collect()
    assert len(rows) == len(docs)
    for r in rows:
        want = plain_counts(docs[r.doc_id])
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want, r.doc_id
        assert r.base_failed == (want[0] < 10 or 100 * want[4] > 20 * want[0])
        assert not (r.base_failed and r.kept)
    good = {r.doc_id: r.quality for r in table(spark, MID, "labels").collect()}
    judged = [(r.kept, good[r.doc_id]) for r in rows if r.doc_id in good and not r.base_failed and zlib.crc32(str(r.doc_id).encode()) % 5 == 0]
    assert np.mean([k for k, g in judged if g == 1]) > 0.95
    assert np.mean([k for k, g in judged if g == 0]) < 0.25


def test_quality_of_odd_rows(spark):
    rows = [(1, None), (2, ""), (3, " \n\t "), (None, "one"), (4, "a b c d e a b c d e\nx\nx"), (4, "a b c d e a b c d e\nx\nx"), (5, "w " * 30000)]
    docs = spark.createDataFrame([(*r, "k") for r in rows], "doc_id long, text string, kept string")
    model = quality.fit_quality(docs, spark.createDataFrame([], "doc_id long, quality int"))
    got = quality.judge_quality(docs, model).collect()
    assert sorted((r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in got) == sorted(plain_counts(t) for _, t in rows)
    assert quality.judge_quality(docs.limit(0), model).count() == 0


def test_blocks_of_any_size_agree():
    rng = random.Random(5)
    texts = ["".join(rng.choice("ab \né漢") for _ in range(rng.randrange(60))) for _ in range(60)] + [None, "", "x" * 500]
    column = pa.array(texts)
    small = [b for b in kernels.blocks(column, 64)]
    large = next(kernels.blocks(column))
    assert sum(b.n for b in small) == large.n == len(texts)
    for k, whole in quality.base_counts(large).items():
        assert np.concatenate([quality.base_counts(b)[k] for b in small]).tolist() == whole.tolist()
    assert np.array([quality.base_counts(large)[k] for k in quality.COUNTS]).T.tolist() == [list(plain_counts(t)) for t in texts]


def plain_segments(values):
    """Maximal segments by their recursive definition: the best one (the earlier and shorter of equals), then left and right of it."""
    best = None
    for a in range(len(values)):
        total = 0
        for b in range(a, len(values)):
            total += values[b]
            if total > 1e-9 and (best is None or total > best[2] + 1e-9 or (abs(total - best[2]) <= 1e-9 and (b - a) < best[1] - best[0] and a == best[0])):
                best = (a, b, total)
    if best is None:
        return []
    a, b, _ = best
    right = [(x + b + 1, y + b + 1, s) for x, y, s in plain_segments(values[b + 1 :])]
    return plain_segments(values[:a]) + [best] + right


def runs_of(values):
    """Runs of positive values: first and last places, and sums before and through each."""
    total = [0.0, *itertools.accumulate(values)]
    firsts = [i for i, v in enumerate(values) if v > 0 and (i == 0 or values[i - 1] <= 0)]
    lasts = [i for i, v in enumerate(values) if v > 0 and (i + 1 == len(values) or values[i + 1] <= 0)]
    return firsts, lasts, [total[i] for i in firsts], [total[i + 1] for i in lasts]


def test_maximal_segments():
    rng = random.Random(1)
    for _ in range(300):
        values = [rng.uniform(-1.5, 1.5) for _ in range(rng.randrange(1, 16))]
        got = toxicity.maximal_segments(*runs_of(values))
        assert [(a, b) for a, b, _ in got] == [(a, b) for a, b, _ in plain_segments(values)]
    assert toxicity.maximal_segments([], [], [], []) == []
    # Of ties the earlier one stays apart.
    assert [x[:2] for x in toxicity.maximal_segments(*runs_of([1.0, -1.0, 1.0]))] == [(0, 0), (2, 2)]


def plain_words(text):
    return [(m.start(), m.end(), m[0]) for m in re.finditer(rb"[a-zA-Z\x80-\xff]+", (text or "").encode())]


def plain_tokens(word):
    low = bytes(b + 32 if 65 <= b <= 90 else b for b in word)
    return [low[:k] for k in toxicity.PREFIXES if len(low) > k] + [low]


def test_word_scores_and_passages_are_the_plain_ones(spark):
    """Log-odds, tolls and segments by plain counting, over whole texts, short and very long."""
    rng = random.Random(8)
    vocabulary = ["tree", "house", "river", "plain", "vilemuck", "vilemuckers", "badly", "stone", "caf\u00e9s", "walking", "walked"]
    rows = []
    for i in range(600):
        toxic = int(i % 5 == 0)
        words = [rng.choice(vocabulary[:4] + vocabulary[7:]) for _ in range(rng.randrange(5, 60))]
        if toxic:
            words[2:4] = rng.choices(vocabulary[4:7], k=3)
        rows.append((i, " ".join(words), toxic))
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")
    model = toxicity.fit_toxicity(docs, spark.createDataFrame([(r[0], r[2]) for r in rows], "doc_id long, toxic int"))
    counts = ({}, {})
    for i, text, toxic in rows:
        if zlib.crc32(str(i).encode()) % 5 > 1:
            own = {}
            for *_, word in plain_words(text):
                for token in plain_tokens(word):
                    own[token] = own.get(token, 0) + 1
            for token, n in own.items():
                counts[toxic][token] = counts[toxic].get(token, 0) + min(n, toxicity.CAP)
    sums = [sum(c.values()) for c in counts]
    odds = {}
    for token in {*counts[0], *counts[1]}:
        c, t = (x.get(token, 0) for x in counts)
        if t + c >= toxicity.MIN_COUNT:
            prior = 0.5 + toxicity.PRIOR * (t + c) / sum(sums)
            t, c = t + prior, c + prior
            raw = math.log(t / (sums[1] + toxicity.PRIOR - t)) - math.log(c / (sums[0] + toxicity.PRIOR - c))
            fourth = (raw / math.sqrt(1 / t + 1 / c) / toxicity.HALF_Z) ** 4
            odds[token] = raw * fourth / (fourth + 1)
    assert any(v < 0 for v in odds.values()) and any(v > 0 for v in odds.values())

    def score(word):
        return max((odds.get(t, 0.0) for t in reversed(plain_tokens(word))), key=abs)

    texts = [*(r[1] for r in rows[:40]), "", None, "Unseen walkers VILEMUCKING tree", " ".join(rng.choices(vocabulary, k=30000))]
    for text in texts:
        block = next(kernels.blocks(pa.array([text], type=pa.string())))
        values = [score(w) for *_, w in plain_words(text)]
        got, _ = model.word_scores(block)
        assert np.allclose(got, values, atol=1e-5)
        paid = [v - model.toll for v in got.tolist()]
        if len(paid) < 200:
            assert [x[:2] for x in model.segments(block)[0][0]] == [x[:2] for x in plain_segments(paid)]
    clean = [score(w) for i, text, toxic in rows if not toxic and zlib.crc32(str(i).encode()) % 5 > 1 for *_, w in plain_words(text)]
    assert abs(model.toll - max(0.0, sum(clean) / len(clean) + toxicity.DRIFT)) < 1e-5


def test_op9_held_out(spark):
    rows = op9_toxicity(spark, MID).collect()
    toxic = {r.doc_id: r.toxic for r in table(spark, MID, "labels").collect()}
    assert len(rows) == table(spark, MID, "documents").count()
    held = [(r.predicted, toxic[r.doc_id]) for r in rows if r.held_out and r.doc_id in toxic]
    assert np.mean([p == t for p, t in held]) > 0.9
    assert np.mean([p for p, t in held if t == 0]) < 0.05
    assert all(0 <= r.score <= 1 for r in rows)


def test_toxic_passages_and_odd_rows(spark):
    labels = [(i, int(i % 4 == 0)) for i in range(400)]
    rng = random.Random(2)
    said = lambda t: " ".join(rng.choice(["vilemuck", "plain", "tree"] if t else ["plain", "tree", "house"]) for _ in range(40))
    docs = spark.createDataFrame([(i, said(t), 0.5) for i, t in labels], "doc_id long, text string, score double")
    model = toxicity.fit_toxicity(docs, spark.createDataFrame(labels, "doc_id long, toxic int"))
    odd = spark.createDataFrame([(1, None, 1.0), (2, "", 1.0), (3, "plain é tree, VILEMUCK vilemuck vilemuck vilemuck! tree " + "house " * 50, 1.0), (None, "tree", 1.0)], docs.schema)
    got = {r.doc_id: r for r in toxicity.score_toxicity(odd, model).collect()}
    assert got[3].score > 0.5 > max(got[1].score, got[2].score, got[None].score)
    (span,) = got[3].passages
    assert (span.start, span.end) == (14, 49)
    assert {r.doc_id for r in toxicity.drop_toxic(odd, model).collect()} == {1, 2, None}
    blank = toxicity.fit_toxicity(docs.limit(0), spark.createDataFrame([], "doc_id long, toxic int"))
    assert [r.score for r in toxicity.score_toxicity(odd, blank).collect()] == [0.0] * 4
