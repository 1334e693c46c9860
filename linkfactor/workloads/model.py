"""Observations, the core model, half-steps, losses and training."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import sources
from ..config import FactorConfig
from ..functions import start_value
from ..operators import factors, gram, smallrank, train
from ..runtime import generation
from . import twins as S
from .twins import REG, UNOBSERVED


def rounded(frame: DataFrame, digits: int = 6, but: tuple[str, ...] = ()) -> DataFrame:
    """Doubles rounded, without negative zeros."""
    return frame.select(*[(F.round(c, digits) + F.lit(0.0)).alias(c) if t == "double" and c not in but else F.col(c) for c, t in frame.dtypes])


def columns_of(obs: DataFrame, rank: int = 2) -> DataFrame:
    return smallrank.init_factors(obs.select("col_id").distinct(), rank, "col_id")


def rows_of(obs: DataFrame, rank: int = 2) -> DataFrame:
    return smallrank.init_factors(obs.select("row_id").distinct(), rank, "row_id")


def as_side(frame: DataFrame, id_name: str, letter: str) -> DataFrame:
    return rounded(frame.select(F.col("id").alias(id_name), *[F.col(f"f{k}").alias(f"{letter}{k}") for k in range(len(frame.columns) - 1)]))


def vectors(frame: DataFrame) -> DataFrame:
    """Wide layout to (id, vec)."""
    return frame.select("id", F.array(*[c for c in frame.columns if c != "id"]).alias("vec"))


def wide(frame: DataFrame, rank: int) -> DataFrame:
    return frame.select("id", *[F.get("vec", k).alias(f"f{k}") for k in range(rank)])


def embeddings(spark: SparkSession, d: str) -> DataFrame:
    return sources.read_table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("vec"))


def obs_purchases(s, d):
    return sources.purchases(s, d).select("row_id", "col_id")


def obs_purchases_weighted(s, d):
    return sources.weighted_purchases(s, d)


def obs_links(s, d):
    return sources.link_observations(s, d)


def obs_words(s, d):
    return sources.tokens(s, d)


def obs_events(s, d):
    return sources.events_as_observations(s, d)


def ids_dictionary(s, d):
    return factors.dictionary(sources.link_observations(s, d), "path").withColumnRenamed("key", "path")


def matrix_row_histories(s, d):
    lists = sources.purchases(s, d).groupBy("row_id").agg(F.collect_list("col_id").alias("col_ids"))
    return lists.select("row_id", F.size("col_ids").alias("n"), F.aggregate("col_ids", F.lit(0).cast("bigint"), lambda a, x: a + x).alias("sum_ids"))


def row_length_profile(s, d):
    n = sources.tokens(s, d).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n"))
    return rounded(n.agg(F.min("n").alias("least"), F.avg("n").alias("mean"), *[F.percentile("n", F.lit(q)).alias(f"p{round(100 * q)}") for q in (0.5, 0.9, 0.99)], F.max("n").alias("most")))


def init_factors(s, d):
    return rounded(columns_of(sources.purchases(s, d)), 9)


def predict_pairs(s, d):
    p = sources.purchases(s, d)
    return rounded(smallrank.predict(p.select("row_id", "col_id"), rows_of(p), columns_of(p)))


def loss_explicit(s, d):
    p = sources.purchases(s, d)
    return rounded(smallrank.loss_explicit(p, rows_of(p), columns_of(p), REG), 5)


def loss_implicit(s, d):
    p = sources.purchases(s, d)
    return rounded(smallrank.loss_implicit(p, rows_of(p), columns_of(p), REG, UNOBSERVED), 5)


def loss_implicit_bruteforce(s, d):
    e = sources.events_as_observations(s, d)
    return rounded(smallrank.loss_implicit(e, rows_of(e), columns_of(e), REG, UNOBSERVED, bruteforce=True), 5)


def gram_small(s, d):
    return rounded(smallrank.gram_columns(columns_of(sources.purchases(s, d))))


def _gram_cells(s, d, fan_in: int | None) -> DataFrame:
    cells = gram.gram_cells(embeddings(s, d), 64, fan_in)
    names = s.createDataFrame([(n, a, b) for n, (a, b) in enumerate((a, b) for a in range(64) for b in range(a, 64))], "pos int, a int, b int")
    return rounded(cells.join(F.broadcast(names), "pos").select("a", "b", "g"), 5)


def gram_embeddings(s, d):
    return _gram_cells(s, d, None)


def gram_tree(s, d):
    return _gram_cells(s, d, 8)


def normal_system(s, d):
    p = sources.purchases(s, d)
    return rounded(smallrank.normal_system(p, columns_of(p)))


def refit_rows(s, d):
    p = sources.purchases(s, d)
    return as_side(smallrank.refit(p, columns_of(p), REG, UNOBSERVED), "row_id", "w")


def refit_rows_explicit(s, d):
    p = sources.purchases(s, d)
    return as_side(smallrank.refit(p, columns_of(p), REG, 0.0), "row_id", "w")


def refit_rows_weighted(s, d):
    p = sources.weighted_purchases(s, d)
    return as_side(smallrank.refit(p, columns_of(p), REG, UNOBSERVED), "row_id", "w")


def refit_cols(s, d):
    p = sources.purchases(s, d)
    return as_side(smallrank.refit(smallrank.transpose(p), rows_of(p), REG, UNOBSERVED), "col_id", "h")


def refit_empty_rows(s, d):
    p = sources.purchases(s, d)
    everyone = sources.read_table(s, d, "customer").select(F.col("c_custkey").alias("id"))
    return as_side(smallrank.refit_all_rows(everyone, p, columns_of(p), REG, UNOBSERVED), "row_id", "w")


def one_epoch(s, d):
    p = sources.purchases(s, d)
    rows = generation(smallrank.refit(p, columns_of(p), REG, UNOBSERVED), "rows")
    return as_side(smallrank.refit(smallrank.transpose(p), rows, REG, UNOBSERVED), "col_id", "h")


def train_loss_curve(s, d):
    e = generation(sources.events_as_observations(s, d), "obs")
    out = None
    for n, (rows, columns) in enumerate(smallrank.epochs(e, columns_of(e), REG, UNOBSERVED, 3, cut=lambda f: generation(f, "side")), 1):
        one = smallrank.loss_implicit(e, rows, columns, REG, UNOBSERVED).select(F.lit(n).alias("epoch"), F.col("total").alias("loss"))
        out = one if out is None else out.unionByName(one)
    return rounded(out, 4)


def train_full(s, d):
    """Rank 16, 8 epochs on purchases: epoch and the terms of the loss."""
    model = train.fit(sources.purchases(s, d), FactorConfig(rank=16, epochs=8, reg=0.01, unobserved=0.01))
    return s.createDataFrame([(int(h["epoch"]), h["observed"], h["all_cells"], h["reg"], h["total"]) for h in model.history], "epoch int, observed double, all_cells double, reg double, total double")


def train_arrays(s, d):
    """Two epochs of the array path at rank 2 from the hashed start: the same columns as the expression path gives."""
    e = sources.events_as_observations(s, d)
    model = train.fit(e, FactorConfig(rank=2, epochs=2, reg=REG, unobserved=UNOBSERVED), track_loss=False, start=vectors(columns_of(e)))
    return as_side(wide(model.col_factors, 2), "col_id", "h")


def model_size(s, d):
    p = sources.purchases(s, d)
    n = p.agg(F.countDistinct("row_id").alias("r"), F.countDistinct("col_id").alias("c"))
    params = (F.col("r") + F.col("c")) * F.lit(128)
    return n.select(params.alias("params"), (params * 4).alias("bytes32"), (params * 2).alias("bytes16"), F.greatest(F.lit(1), F.ceil(params * F.lit(2.0) / F.lit(float(16 << 30)))).cast("bigint").alias("min_executors"))


def recency_weighted_obs(s, d):
    e = sources.read_table(s, d, "events").select("user_id", F.get_json_object("props", "$.k").cast("bigint").alias("k"), F.datediff(F.lit("2024-02-01").cast("date"), F.col("ts")).alias("age"))
    return rounded(e.groupBy(F.col("user_id").alias("row_id"), F.col("k").alias("col_id")).agg(F.sum(F.exp(-F.col("age") / F.lit(10.0))).alias("y")))


def dictionary_start(s, d):
    """Column expressions of the start over dictionary ids of link paths."""
    table = factors.dictionary(sources.link_observations(s, d), "path")
    hashed: list[Column] = [start_value(F.col("id"), k).alias(f"f{k}") for k in range(2)]
    return rounded(table.select("key", "id", *hashed), 9)


_OBS_H = f"WITH {S.P}, {S.factors('h', 'p', 'col_id')}"
_OBS_WH = f"WITH {S.P}, {S.factors('h', 'p', 'col_id')}, {S.factors('w', 'p', 'row_id')}"
_GRAM_SQL = "WITH x AS (SELECT unnest(range(0, 64)) AS i), v AS (SELECT vec_id, i, embedding[i + 1]::double AS v FROM embeddings, x) SELECT a.i::integer AS a, b.i::integer AS b, round(sum(a.v * b.v), 5) + 0.0 AS g FROM v a JOIN v b ON a.vec_id = b.vec_id AND a.i <= b.i GROUP BY a.i, b.i"


def _loss_sql(cte: str, obs: str, digits: int = 5) -> str:
    return f"{cte} SELECT {S.rounded(['observed', 'all_cells', 'reg', 'total'], digits)} FROM ({S.loss(obs, 'w', 'h')})"


def _epochs_sql(n: int) -> str:
    parts = [S.E, S.factors("h0", "e", "col_id"), S.back("eb", "e")]
    for k in range(n):
        parts += [S.refit(f"w{k + 1}", "e", f"h{k}"), S.refit(f"h{k + 1}", "eb", f"w{k + 1}")]
    return "WITH " + ", ".join(parts)


SQL = {
    "obs_purchases": f"WITH {S.P} SELECT row_id, col_id FROM p",
    "obs_purchases_weighted": "SELECT o_custkey AS row_id, l_partkey AS col_id, sum(l_quantity) AS y FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2",
    "obs_links": f"WITH {S.L} SELECT * FROM l",
    "obs_words": f"WITH {S.T} SELECT * FROM t",
    "obs_events": f"WITH {S.E} SELECT * FROM e",
    "ids_dictionary": f"WITH {S.L} SELECT path, row_number() OVER (ORDER BY path) - 1 AS id FROM (SELECT DISTINCT path FROM l)",
    "dictionary_start": f"WITH {S.L} SELECT key, id, round({S.start(0)}, 9) + 0.0 AS f0, round({S.start(1)}, 9) + 0.0 AS f1 FROM (SELECT path AS key, row_number() OVER (ORDER BY path) - 1 AS id FROM (SELECT DISTINCT path FROM l))",
    "matrix_row_histories": f"WITH {S.P} SELECT row_id, count(*)::integer AS n, sum(col_id)::bigint AS sum_ids FROM p GROUP BY row_id",
    "row_length_profile": f"WITH {S.T}, n AS (SELECT count(*) AS n FROM t GROUP BY doc_id) SELECT min(n) AS least, round(avg(n), 6) AS mean, round(quantile_cont(n, 0.5), 6) AS p50, round(quantile_cont(n, 0.9), 6) AS p90, round(quantile_cont(n, 0.99), 6) AS p99, max(n) AS most FROM n",
    "init_factors": f"{_OBS_H} SELECT id, {S.rounded(['f0', 'f1'], 9)} FROM h",
    "predict_pairs": f"{_OBS_WH} SELECT row_id, col_id, round(w.f0 * h.f0 + w.f1 * h.f1, 6) + 0.0 AS score FROM p JOIN w ON row_id = w.id JOIN h ON col_id = h.id",
    "loss_explicit": f"{_OBS_WH} SELECT round(o, 5) + 0.0 AS observed, round(a, 5) + 0.0 AS reg_row, round(b, 5) + 0.0 AS reg_col, round(o + a + b, 5) + 0.0 AS total FROM (SELECT (SELECT sum((y - s) * (y - s)) FROM (SELECT y, w.f0 * h.f0 + w.f1 * h.f1 AS s FROM p JOIN w ON row_id = w.id JOIN h ON col_id = h.id)) AS o, {REG}::double * (SELECT sum(f0 * f0 + f1 * f1) FROM w) AS a, {REG}::double * (SELECT sum(f0 * f0 + f1 * f1) FROM h) AS b)",
    "loss_implicit": _loss_sql(_OBS_WH, "p"),
    "loss_implicit_bruteforce": _loss_sql(f"WITH {S.E}, {S.factors('h', 'e', 'col_id')}, {S.factors('w', 'e', 'row_id')}", "e"),
    "gram_small": f"{_OBS_H}, {S.gram('g', 'h')} SELECT {S.rounded(['g00', 'g01', 'g11'])} FROM g",
    "gram_embeddings": _GRAM_SQL,
    "gram_tree": _GRAM_SQL,
    "normal_system": f"{_OBS_H}, {S.system('s', 'p', 'h')} SELECT row_id, {S.rounded(['a00', 'a01', 'a11', 'b0', 'b1'])}, n FROM s",
    "refit_rows": f"{_OBS_H}, {S.refit('w', 'p', 'h')} SELECT id AS row_id, round(f0, 6) + 0.0 AS w0, round(f1, 6) + 0.0 AS w1 FROM w",
    "refit_rows_explicit": f"{_OBS_H}, {S.refit('w', 'p', 'h', weight=0.0)} SELECT id AS row_id, round(f0, 6) + 0.0 AS w0, round(f1, 6) + 0.0 AS w1 FROM w",
    "refit_rows_weighted": f"WITH p AS (SELECT o_custkey AS row_id, l_partkey AS col_id, sum(l_quantity) AS y FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2), {S.factors('h', 'p', 'col_id')}, {S.refit('w', 'p', 'h')} SELECT id AS row_id, round(f0, 6) + 0.0 AS w0, round(f1, 6) + 0.0 AS w1 FROM w",
    "refit_cols": f"WITH {S.P}, {S.factors('w', 'p', 'row_id')}, {S.back('b', 'p')}, {S.refit('h', 'b', 'w')} SELECT id AS col_id, round(f0, 6) + 0.0 AS h0, round(f1, 6) + 0.0 AS h1 FROM h",
    "refit_empty_rows": f"{_OBS_H}, {S.refit('w', 'p', 'h')} SELECT c_custkey AS row_id, round(coalesce(f0, 0.0), 6) + 0.0 AS w0, round(coalesce(f1, 0.0), 6) + 0.0 AS w1 FROM customer LEFT JOIN w ON c_custkey = id",
    "one_epoch": f"{_OBS_H}, {S.back('b', 'p')}, {S.refit('w', 'p', 'h')}, {S.refit('h1', 'b', 'w')} SELECT id AS col_id, round(f0, 6) + 0.0 AS h0, round(f1, 6) + 0.0 AS h1 FROM h1",
    "train_loss_curve": f"{_epochs_sql(3)} " + " UNION ALL ".join(f"SELECT {k} AS epoch, round(total, 4) + 0.0 AS loss FROM ({S.loss('e', f'w{k}', f'h{k}')})" for k in (1, 2, 3)),
    "train_arrays": f"{_epochs_sql(2)} SELECT id AS col_id, round(f0, 6) + 0.0 AS h0, round(f1, 6) + 0.0 AS h1 FROM h2",
    "model_size": f"WITH {S.P}, n AS (SELECT (count(DISTINCT row_id) + count(DISTINCT col_id)) * 128 AS params FROM p) SELECT params, params * 4 AS bytes32, params * 2 AS bytes16, greatest(1, ceil(params * 2.0 / 17179869184.0))::bigint AS min_executors FROM n",
    "recency_weighted_obs": "SELECT user_id AS row_id, json_extract_string(props, '$.k')::bigint AS col_id, round(sum(exp(-date_diff('day', ts::date, DATE '2024-02-01') / 10.0::double)), 6) + 0.0 AS y FROM events GROUP BY 1, 2",
}
QUERIES = {k: globals()[k] for k in [*SQL, "train_full"]}
