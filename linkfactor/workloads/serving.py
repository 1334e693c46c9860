"""Fold-in, retrieval, splits, ranking measures and the grid."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import sources
from ..operators import evaluate, smallrank, topk
from ..operators.graph import host_of
from ..operators.split import strong_split
from ..runtime import generation
from . import twins as S
from .model import as_side, columns_of, embeddings, rounded, vectors
from .twins import REG, UNOBSERVED

REGS = (5e-2, 1e-2, 5e-3, 1e-3, 5e-4, 1e-4)
WEIGHTS = (1e-3, 5e-4, 1e-4, 5e-5, 1e-5, 5e-6, 1e-6)


def event_split(s, d) -> DataFrame:
    return strong_split(sources.events_as_observations(s, d), "row_id", "col_id")


def fold_in(s, d):
    """Vectors of the test users from their given cells, columns frozen at the hashed start."""
    split = event_split(s, d)
    h = columns_of(sources.events_as_observations(s, d))
    return as_side(smallrank.refit(split.where("role = 'given'"), h, REG, UNOBSERVED), "row_id", "w")


def queries_of(v: DataFrame) -> DataFrame:
    """The rows that are asked for in a search against all: those whose id is divisible by 20."""
    return v.where("id % 20 = 0")


def _neighbours(s, d, method, asked=lambda v: v) -> DataFrame:
    v = embeddings(s, d)
    return method(asked(v), v).select(F.col("row_id").alias("vec_id"), "rank", F.col("col_id").alias("nbr"))


def topk_exact(s, d):
    return _neighbours(s, d, lambda a, b: topk.topk_exact(a, b, 10, 64, digits=6))


def topk_sort(s, d):
    return _neighbours(s, d, lambda a, b: topk.topk_sort(a, b, 10, digits=6))


def topk_lsh(s, d):
    return _neighbours(s, d, lambda a, b: topk.topk_lsh(a, b, 10, 64), queries_of)


def topk_ivf(s, d):
    return _neighbours(s, d, lambda a, b: topk.topk_ivf(a, b, 10, 64))


def topk_exclude_given(s, d):
    """The best five columns for each test user, given ones left out."""
    split, e = event_split(s, d), sources.events_as_observations(s, d)
    h = columns_of(e)
    w = smallrank.refit(split.where("role = 'given'"), h, REG, UNOBSERVED)
    ranked = topk.topk_exact(vectors(w), vectors(h), 5, 2, exclude=split.where("role = 'given'"), digits=6)
    return ranked.select("row_id", "rank", "col_id")


def ann_recall(s, d):
    """method, k, recall of the approximate searches against the exact one, for the rows whose id is divisible by 20 against all."""
    v = embeddings(s, d)
    q = queries_of(v)
    exact, lsh, ivf = (generation(found, "found") for found in (topk.topk_exact(q, v, 50, 64), topk.topk_lsh(q, v, 50, 64), topk.topk_ivf(q, v, 50, 64)))
    lsh = evaluate.overlap(lsh, exact, (20, 50)).select(F.lit("lsh").alias("method"), "k", "recall")
    ivf = evaluate.overlap(ivf, exact, (20, 50)).select(F.lit("ivf").alias("method"), "k", "recall")
    return lsh.unionByName(ivf)


def split_strong(s, d):
    return strong_split(sources.link_observations(s, d), "page_id", "path")


def _ranked_events(s, d, k: int) -> tuple[DataFrame, DataFrame]:
    split, e = event_split(s, d), sources.events_as_observations(s, d)
    h = columns_of(e)
    given = split.where("role = 'given'")
    w = smallrank.refit(given, h, REG, UNOBSERVED)
    return topk.topk_exact(vectors(w), vectors(h), k, 2, exclude=given, digits=6), split.where("role = 'hidden'")


def recall_at_k(s, d):
    ranked, hidden = _ranked_events(s, d, 50)
    return rounded(evaluate.recall(ranked, hidden))


def ranking_metrics(s, d):
    ranked, hidden = _ranked_events(s, d, 20)
    return rounded(evaluate.ranking_measures(ranked, hidden))


def _links(s, d) -> DataFrame:
    return split_strong(s, d).select(F.col("page_id").alias("row_id"), F.col("path").alias("col_id"), "role")


def recall_popularity(s, d):
    x = _links(s, d)
    ranked = evaluate.popularity_topk(x.where("role = 'train'"), x.where("role = 'given'"), 50, exclude=x.where("role = 'given'"))
    return rounded(evaluate.recall(ranked, x.where("role = 'hidden'")).drop("recall_capped"))


def recall_random(s, d):
    x = _links(s, d)
    ranked = evaluate.random_topk(x.where("role = 'train'"), x.where("role = 'hidden'"), 50)
    return rounded(evaluate.recall(ranked, x.where("role = 'hidden'")).drop("recall_capped"))


def _grid(s, d) -> DataFrame:
    """One half-step of all 42 pairs of weights in a single plan: systems are built once and crossed with the grid."""
    e = sources.events_as_observations(s, d)
    h = columns_of(e)
    points = s.createDataFrame([(i * len(WEIGHTS) + j, r, a) for i, r in enumerate(REGS) for j, a in enumerate(WEIGHTS)], "point int, reg double, unobserved double")
    grams = smallrank.gram_columns(h)
    systems = smallrank.normal_system(e, h).crossJoin(F.broadcast(grams)).crossJoin(F.broadcast(points))
    ridged = systems.withColumns({"a00": F.col("a00") + F.col("unobserved") * F.col("g00") + F.col("reg"), "a01": F.col("a01") + F.col("unobserved") * F.col("g01"), "a11": F.col("a11") + F.col("unobserved") * F.col("g11") + F.col("reg")})
    w = ridged.select("point", "reg", "unobserved", F.col("row_id").alias("w_id"), *[x.alias(f"w{k}") for k, x in enumerate(smallrank.solve2())])
    gathered = e.join(h, F.col("col_id") == F.col("id")).join(w, F.col("row_id") == F.col("w_id"))
    miss = F.col("y") - (F.col("w0") * F.col("f0") + F.col("w1") * F.col("f1"))
    errors = gathered.groupBy("point").agg(F.sum(miss * miss).alias("observed"))
    moments = w.groupBy("point", "reg", "unobserved").agg(F.sum(F.col("w0") * F.col("w0")).alias("xx"), F.sum(F.col("w0") * F.col("w1")).alias("xy"), F.sum(F.col("w1") * F.col("w1")).alias("yy"))
    cells = F.col("xx") * F.col("g00") + 2 * F.col("xy") * F.col("g01") + F.col("yy") * F.col("g11")
    loss = F.col("observed") + F.col("unobserved") * cells + F.col("reg") * (F.col("xx") + F.col("yy") + F.col("g00") + F.col("g11"))
    return errors.join(moments, "point").crossJoin(F.broadcast(grams)).select("reg", "unobserved", loss.alias("loss"))


def grid_search(s, d):
    return rounded(_grid(s, d), but=("reg", "unobserved"))


def grid_best(s, d):
    one = rounded(_grid(s, d), but=("reg", "unobserved")).agg(F.min_by(F.struct("reg", "unobserved"), F.struct("loss", "reg", "unobserved")).alias("at"))
    return one.select(F.lit("events").alias("graph"), "at.reg", "at.unobserved")


def same_host_share(s, d):
    """Of the ten nearest pages by embedding, the share of the own host, and the base rate of two random pages."""
    hosts = sources.read_table(s, d, "pages").select(F.col("page_id").alias("id"), host_of(F.col("url")).alias("attr"))
    v = embeddings(s, d).join(hosts.select("id"), "id", "left_semi")
    ranked = topk.topk_exact(v, v, 10, 64, exclude=v.select(F.col("id").alias("row_id"), F.col("id").alias("col_id")), digits=6)
    return rounded(evaluate.same_attribute_share(ranked, hosts, 10))


def spot_check(s, d):
    ranked, _ = _ranked_events(s, d, 5)
    users = ranked.select(F.col("row_id").alias("id")).distinct().withColumn("key", F.concat(F.lit("user "), F.col("id")))
    keys = ranked.select(F.col("col_id").alias("id")).distinct().withColumn("key", F.concat(F.lit("k "), F.col("id")))
    return rounded(evaluate.spot_check(ranked, users, keys, 3))


def _split_sql(obs: str, src: str, dst: str, more: str = "") -> str:
    """CTE sp: obs with its role."""
    key, cell = f"md5('s' || {src})", f"md5('s|' || {src} || '|' || {dst})"
    return (
        f"sb AS (SELECT *, ('0x' || substr({key}, 1, 8))::bigint % 100 >= 90 AS test FROM {obs}), "
        f"sn AS (SELECT *, row_number() OVER (PARTITION BY {src} ORDER BY {cell}, {dst}::varchar) AS place, count(*) OVER (PARTITION BY {src}) AS deg FROM sb), "
        f"sp AS (SELECT {src}, {dst}{more}, CASE WHEN NOT test THEN 'train' WHEN place <= floor(0.25::double * deg) THEN 'hidden' ELSE 'given' END AS role FROM sn)"
    )


_EV = f"WITH {S.E}, {S.factors('h', 'e', 'col_id')}, {_split_sql('e', 'row_id', 'col_id', ', y')}, gv AS (SELECT row_id, col_id, y FROM sp WHERE role = 'given'), {S.refit('w', 'gv', 'h')}"
_EV_RANKED = (
    f"{_EV}, sc AS (SELECT w.id AS row_id, h.id AS col_id, round(w.f0 * h.f0 + w.f1 * h.f1, 6) AS score FROM w, h WHERE NOT EXISTS (SELECT 1 FROM gv WHERE gv.row_id = w.id AND gv.col_id = h.id)), "
    "rk AS (SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY score DESC, col_id) AS rank FROM sc), hd AS (SELECT row_id, col_id FROM sp WHERE role = 'hidden'), tr AS (SELECT row_id, count(*) AS truth FROM hd GROUP BY 1)"
)
_NEAR = (
    "WITH x AS (SELECT unnest(range(0, 64)) AS i), v AS (SELECT vec_id, i, embedding[i + 1]::double AS v FROM embeddings, x), "
    "sc AS (SELECT a.vec_id, b.vec_id AS nbr, round(sum(a.v * b.v), 6) AS score FROM v a JOIN v b ON a.i = b.i GROUP BY 1, 2), "
    "rk AS (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY score DESC, nbr) AS rank FROM sc) SELECT vec_id, rank::integer AS rank, nbr FROM rk WHERE rank <= 10"
)
_LK = f"WITH {S.L}, {_split_sql('l', 'page_id', 'path')}, hd AS (SELECT page_id AS row_id, path AS col_id FROM sp WHERE role = 'hidden'), tr AS (SELECT row_id, count(*) AS truth FROM hd GROUP BY 1)"


def _recall_sql(cte: str, capped: bool) -> str:
    one = "SELECT {k} AS k, round(avg(hits / truth::double), 6) + 0.0 AS recall_truth{c}, count(*) AS n_sources FROM (SELECT tr.row_id, truth, count(rk.col_id) AS hits FROM tr LEFT JOIN hd ON tr.row_id = hd.row_id LEFT JOIN rk ON rk.row_id = hd.row_id AND rk.col_id = hd.col_id AND rk.rank <= {k} GROUP BY 1, 2)"
    more = ", round(avg(hits / least({k}, truth)::double), 6) + 0.0 AS recall_capped"
    return f"{cte} " + " UNION ALL ".join(one.format(k=k, c=more.format(k=k) if capped else "") for k in (20, 50))


def _grid_sql() -> str:
    points = ", ".join(f"({r!r}::double, {a!r}::double)" for r in REGS for a in WEIGHTS)
    return (
        f"WITH {S.E}, {S.factors('h', 'e', 'col_id')}, {S.gram('g', 'h')}, {S.system('sy', 'e', 'h')}, pt(reg, unobserved) AS (VALUES {points}), "
        "rr AS (SELECT reg, unobserved, row_id, a00 + unobserved * g00 + reg AS a00, a01 + unobserved * g01 AS a01, a11 + unobserved * g11 + reg AS a11, b0, b1 FROM sy, g, pt), "
        "w AS (SELECT reg, unobserved, row_id AS w_id, (a11 * b0 - a01 * b1) / (a00 * a11 - a01 * a01) AS w0, (a00 * b1 - a01 * b0) / (a00 * a11 - a01 * a01) AS w1 FROM rr), "
        "er AS (SELECT reg, unobserved, sum((y - (w0 * f0 + w1 * f1)) * (y - (w0 * f0 + w1 * f1))) AS observed FROM e JOIN h ON col_id = id JOIN w ON row_id = w_id GROUP BY 1, 2), "
        "mo AS (SELECT reg, unobserved, sum(w0 * w0) AS xx, sum(w0 * w1) AS xy, sum(w1 * w1) AS yy FROM w GROUP BY 1, 2), "
        "gr AS (SELECT er.reg, er.unobserved, round(observed + er.unobserved * (xx * g00 + 2 * xy * g01 + yy * g11) + er.reg * (xx + yy + g00 + g11), 6) + 0.0 AS loss FROM er JOIN mo ON er.reg = mo.reg AND er.unobserved = mo.unobserved, g) "
    )


SQL = {
    "fold_in": f"{_EV} SELECT id AS row_id, round(f0, 6) + 0.0 AS w0, round(f1, 6) + 0.0 AS w1 FROM w",
    "topk_exact": _NEAR,
    "topk_sort": _NEAR,
    "topk_exclude_given": f"{_EV_RANKED} SELECT row_id, rank::integer AS rank, col_id FROM rk WHERE rank <= 5",
    "split_strong": f"WITH {S.L}, {_split_sql('l', 'page_id', 'path')} SELECT * FROM sp",
    "recall_at_k": _recall_sql(_EV_RANKED, True),
    "ranking_metrics": f"{_EV_RANKED}, ht AS (SELECT hd.row_id, count(*) AS hits, sum(1.0::double / log2(rank + 1.0::double)) AS dcg, min(rank) AS first FROM hd JOIN rk ON rk.row_id = hd.row_id AND rk.col_id = hd.col_id AND rk.rank <= 20 GROUP BY 1), ea AS (SELECT tr.row_id, truth, coalesce(hits, 0) AS hits, coalesce(dcg, 0.0::double) AS dcg, coalesce(1.0::double / first, 0.0::double) AS rr, (SELECT sum(1.0::double / log2(i + 1.0::double)) FROM range(1, 21) z(i) WHERE i <= truth) AS ideal FROM tr LEFT JOIN ht ON tr.row_id = ht.row_id) SELECT 20 AS k, round(avg(hits / 20.0::double), 6) + 0.0 AS precision, round(avg(dcg / ideal), 6) + 0.0 AS ndcg, round(avg(rr), 6) + 0.0 AS mrr FROM ea",
    "recall_popularity": _recall_sql(f"{_LK}, gv AS (SELECT page_id AS row_id, path AS col_id FROM sp WHERE role = 'given'), us AS (SELECT path AS col_id, count(*) AS uses FROM sp WHERE role = 'train' GROUP BY 1), rk AS (SELECT row_id, col_id, row_number() OVER (PARTITION BY row_id ORDER BY uses DESC, col_id) AS rank FROM (SELECT DISTINCT row_id FROM gv) q, us WHERE NOT EXISTS (SELECT 1 FROM gv WHERE gv.row_id = q.row_id AND gv.col_id = us.col_id))", False),
    "recall_random": _recall_sql(f"{_LK}, cs AS (SELECT DISTINCT path AS col_id FROM sp WHERE role = 'train'), rk AS (SELECT row_id, col_id, row_number() OVER (PARTITION BY row_id ORDER BY ('0x' || substr(md5('r' || row_id || '|' || col_id), 1, 8))::bigint, col_id) AS rank FROM (SELECT DISTINCT row_id FROM hd) q, cs)", False),
    "grid_search": f"{_grid_sql()} SELECT * FROM gr",
    "same_host_share": (
        "WITH ho AS (SELECT page_id AS id, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host FROM pages), x AS (SELECT unnest(range(0, 64)) AS i), v AS (SELECT vec_id, i, embedding[i + 1]::double AS v FROM embeddings, x WHERE vec_id IN (SELECT id FROM ho)), "
        "sc AS (SELECT a.vec_id, b.vec_id AS nbr, round(sum(a.v * b.v), 6) AS score FROM v a JOIN v b ON a.i = b.i AND a.vec_id <> b.vec_id GROUP BY 1, 2), "
        "rk AS (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY score DESC, nbr) AS rank FROM sc), sz AS (SELECT host, count(*)::double AS n FROM ho GROUP BY 1) "
        "SELECT 10 AS k, round(avg(CASE WHEN a.host = b.host THEN 1.0::double ELSE 0.0::double END), 6) + 0.0 AS share, (SELECT round(sum(n * (n - 1)) / (sum(n) * (sum(n) - 1)), 6) + 0.0 FROM sz) AS base_rate FROM rk JOIN ho a ON vec_id = a.id JOIN ho b ON nbr = b.id WHERE rank <= 10"
    ),
    "spot_check": f"{_EV_RANKED} SELECT 'user ' || row_id AS row_key, rank::integer AS rank, 'k ' || col_id AS col_key, score + 0.0 AS score FROM rk WHERE rank <= 3",
    "grid_best": f"{_grid_sql()} SELECT 'events' AS graph, reg, unobserved FROM gr ORDER BY loss, reg, unobserved LIMIT 1",
}
QUERIES = {k: globals()[k] for k in [*SQL, "topk_lsh", "topk_ivf", "ann_recall"]}
