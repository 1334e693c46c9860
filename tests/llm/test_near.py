"""Near-duplicate operators against brute force."""

import random
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from linkfactor.llm import near, near_docs
from linkfactor.llm.cluster import table
from linkfactor.llm.kernels import blocks
from linkfactor.llm.queries_near import op8_near_dedup

MID = "/root/testdata/sf0.01"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text)


def plain_set(text, width):
    words = WORD.findall(lower(text or ""))
    return {tuple(words[i : i + width]) for i in range(len(words) - width + 1)} if len(words) >= width else {tuple(words)} if words else set()


def plain_components(rows, width):
    sets = {k: plain_set(t, width) for k, t in rows}
    root = {k: k for k in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    holders = {}
    for k, s in sets.items():
        for x in s:
            holders.setdefault(x, []).append(k)
    common = {}
    for at in holders.values():
        for i, x in enumerate(at):
            for y in at[i + 1 :]:
                common[x, y] = common.get((x, y), 0) + 1
    for (x, y), n in common.items():
        if 100 * n >= 80 * (len(sets[x]) + len(sets[y]) - n):
            a, b = find(x), find(y)
            root[max(a, b)] = min(a, b)
    return {k: (len(s), find(k)) for k, s in sets.items()}


def test_op8_is_brute_force(spark):
    rows = [(r.doc_id, r.text) for r in table(spark, MID, "documents").collect()]
    want = plain_components(rows, 4)
    got = {r.doc_id: r for r in op8_near_dedup(spark, MID).collect()}
    assert {k: (r.n_shingles, r.component_id) for k, r in got.items()} == want
    assert all(r.kept == (r.doc_id == r.component_id) for r in got.values())


def test_near_of_odd_rows_chains_and_hubs(spark):
    rng = random.Random(3)
    base = [f"w{rng.randrange(10**6)}" for _ in range(120)]
    rows = [(1, None), (2, ""), (3, " \t"), (4, "Ab c"), (5, "aB C"), (6, "ab c d"), (7, "x"), (7, "x"), (None, "x"), (8, "long " * 20000)]
    text = list(base)
    for k in range(12):  # a chain: each differs from the last by a word
        rows.append((100 - k, " ".join(text)))
        text[10 * k] = f"n{k}"
    for k in range(60):  # a hub with copies that differ from each other by more than from it
        text = list(base)
        text[1 + k] = text[60 + k % 59] = f"h{k}"
        rows.append((1000 + k, " ".join(text)))
    docs = spark.createDataFrame([(*r, 0) for r in rows], "doc_id long, text string, component_id int")
    want = plain_components([r for r in rows if r[0] is not None], 4)
    got = near_docs.near_components(docs, width=4).collect()
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got if r.doc_id is not None} == want
    assert len(got) == len(rows) and all(r.kept for r in got if r.doc_id is None)
    kept = near_docs.drop_near_copies(docs, width=4)
    assert sorted(kept.columns) == sorted(docs.columns)
    assert sorted((r.doc_id or 0) for r in kept.collect()) == sorted([0] + [k for k, *_ in rows if k is not None and want[k][1] == k])
    assert near_docs.near_components(docs.limit(0)).count() == 0


def test_connected(spark):
    rng = random.Random(4)
    edges = [(rng.randrange(300), rng.randrange(300)) for _ in range(260)] + [(1000 + i, 1001 + i) for i in range(40)] + [(5, 5)]
    root = {x: x for e in edges for x in e}
    for _ in range(300):
        for a, b in edges:
            root[a] = root[b] = min(root[a], root[b])
    got = {r.node: r.root for r in near.connected(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {k: v for k, v in root.items() if k in got}
    assert set(got) == {x for a, b in edges if a != b for x in (a, b)}
    assert near.connected(spark.createDataFrame([], "a long, b long")).count() == 0


def plain_superminhash(values, slots):
    """One text, member by member, with real swaps."""
    best = [None] * slots
    for v in values:
        order, state = list(range(slots)), np.array([v], dtype=np.uint64)
        for step in range(slots):
            state = near_docs.mix(state)
            pick = step + (int(state[0]) >> 32) * (slots - step) // 2**32
            order[step], order[pick] = order[pick], order[step]
            offer = step << 56 | int(near_docs.mix(state ^ np.uint64(0xA5A5A5A5))[0]) >> 8
            if best[order[step]] is None or offer < best[order[step]]:
                best[order[step]] = offer
    return best


def test_long_documents_whose_sketches_differ_by_chance_are_linked(spark):
    words = [f"s592w{i}" for i in range(2225)]  # of 1500 such pairs one whose samples differ this much
    rows = [(1, " ".join(words[:2003])), (2, " ".join(words[222:]))]
    block = next(blocks(pa.array([t for _, t in rows])))
    a, b = near_docs.sketch_longs(near_docs.superminhash(*near_docs.shingle_sets(block, 4))).view(np.int64).tolist()
    longs = near_docs.SLOTS * near_docs.SAMPLE_BITS // 64
    assert spark.createDataFrame([(a, b)], "a array<long>, b array<long>").select(near.mismatches(F.col("a"), F.col("b"), longs, near_docs.SAMPLE_BITS).alias("n")).first().n == 67
    got = near_docs.near_components(spark.createDataFrame(rows, "doc_id long, text string"), width=4).collect()
    want = plain_components(rows, 4)
    assert want[2] == (2000, 1) and {r.doc_id: (r.n_shingles, r.component_id) for r in got} == want


def test_superminhash_stops_early_with_the_full_result():
    texts = ["a b c d e f g", " ".join(map(str, range(300))), "x", " ".join(map(str, range(40, 330)))]
    block = next(blocks(pa.array(texts)))
    sets, bounds = near_docs.shingle_sets(block, 4)
    got = near_docs.superminhash(sets, bounds, 32)
    for i in range(len(texts)):
        assert got[i].tolist() == plain_superminhash(sets[bounds[i] : bounds[i + 1]].tolist(), 32)
    wide = near_docs.superminhash(sets, bounds, 128)
    a, b = (set(sets[bounds[i] : bounds[i + 1]].tolist()) for i in (1, 3))
    assert abs((wide[1] == wide[3]).mean() - len(a & b) / len(a | b)) < 0.12


def test_sketches_count_differing_samples(spark):
    rows = [([0b11_01_00, -1], [0b11_00_10, -1 ^ (3 << 60)])]
    frame = spark.createDataFrame(rows, "a array<long>, b array<long>")
    assert frame.select(near.mismatches(F.col("a"), F.col("b"), 2, 2).alias("n")).first().n == 3
    assert frame.select(near.mismatches(F.col("a"), F.col("b"), 2, 4).alias("n")).first().n == 2
