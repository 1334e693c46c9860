"""The pipeline against plain versions of its stages."""

import math
from hashlib import md5

from pyspark.sql import functions as F

import corpus_pipeline
from linkfactor.llm import mixing
from linkfactor.llm.cluster import table
from linkfactor.llm.pieces import RATE, SEED

from .test_lines import plain_dedup
from .test_near import plain_components
from .test_pieces import Agenda

MID = "/root/testdata/sf0.01"


def test_stage_order():
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line_dedup", "near_dedup", "mixing", "sentencepiece"]


def test_pipeline_on_its_own_stages(spark):
    docs = table(spark, MID, "documents")
    before = {r.doc_id: r for r in docs.collect()}
    left = corpus_pipeline.drop_toxic(spark, docs, MID).cache()
    toxic = {r.doc_id for r in table(spark, MID, "labels").where("toxic = 1").collect()}
    clean = {r.doc_id for r in table(spark, MID, "labels").where("toxic = 0").collect()}
    stay = {r.doc_id for r in left.collect()}
    assert len(clean - stay) <= 0.02 * len(clean) and len(toxic & stay) <= 0.2 * len(toxic)
    assert left.columns == docs.columns

    lined = corpus_pipeline.dedup_lines(spark, left, MID).cache()
    want = dict(plain_dedup([(k, before[k].text) for k in stay]))
    got = {r.doc_id: r for r in lined.collect()}
    assert lined.columns == docs.columns and set(got) == stay
    assert sum(got[k].text != t for k, t in want.items()) <= 4
    assert all(r.n_chars == len(r.text) for r in got.values() if r.text != before[r.doc_id].text)

    single = corpus_pipeline.drop_near_copies(spark, lined, MID).cache()
    want = {k for k, (_, c) in plain_components([(k, r.text) for k, r in got.items()], 5).items() if c == k}
    assert single.columns == docs.columns and {r.doc_id for r in single.collect()} == want

    mixed = corpus_pipeline.mix_sources(spark, single, MID).cache()
    rows = {r.doc_id: r for r in single.collect()}
    sizes = {}
    for r in rows.values():
        sizes[r.source] = sizes.get(r.source, 0) + 1
    counts = {}
    for r in mixed.collect():
        counts[r.doc_id] = counts.get(r.doc_id, 0) + 1
    for k, r in rows.items():
        rate, u = len(rows) / len(sizes) / sizes[r.source], int(md5(f"{mixing.SEED}|{k}".encode()).hexdigest()[:13], 16) / 16**13
        n, p = 0, math.exp(-rate)
        total = p
        while u >= total:
            n += 1
            p *= rate / n
            total += p
        assert counts.get(k, 0) == n
    assert mixed.columns == docs.columns

    coded = corpus_pipeline.encode_pieces(spark, mixed, MID).collect()
    assert len(coded) == sum(counts.values())
    agenda = Agenda(SEED, RATE)
    salt = {r.doc_id: r.salt for r in mixed.select("doc_id", F.xxhash64(F.lit("dropout"), F.col("doc_id").cast("string")).alias("salt")).distinct().collect()}
    for r in coded[:20]:
        assert r.lossless and r.ids == agenda.text(rows[r.doc_id].text, salt[r.doc_id])


def test_run(spark):
    rows = corpus_pipeline.run(spark, "/root/testdata/sf0.001").collect()
    assert rows and all(r.lossless for r in rows)
