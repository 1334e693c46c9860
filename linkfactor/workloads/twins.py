"""Pieces of SQL that the twins are put together from."""

from __future__ import annotations

REG, UNOBSERVED = 0.1, 0.01

P = "p AS (SELECT DISTINCT o_custkey AS row_id, l_partkey AS col_id, 1.0::double AS y FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"
E = "e AS (SELECT user_id AS row_id, json_extract_string(props, '$.k')::bigint AS col_id, count(*)::double AS y FROM events GROUP BY 1, 2)"
L = "l AS (SELECT DISTINCT page_id, path FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS path FROM pages) WHERE path <> '')"
T = "t AS (SELECT DISTINCT doc_id, word FROM (SELECT doc_id, unnest(regexp_extract_all(lower(text), '(\\p{L}+)', 1)) AS word FROM documents))"


def start(dim: int, entity: str = "id") -> str:
    return f"((({entity}) * 7919 + {(dim + 1) * 104729}) % 1000003)::double / 1000003.0::double - 0.5::double"


def factors(name: str, obs: str, column: str, rank: int = 2) -> str:
    return f"{name} AS (SELECT id, {', '.join(f'{start(k)} AS f{k}' for k in range(rank))} FROM (SELECT DISTINCT {column} AS id FROM {obs}))"


def back(name: str, obs: str) -> str:
    return f"{name} AS (SELECT col_id AS row_id, row_id AS col_id, y FROM {obs})"


def pairs(rank: int) -> list[tuple[int, int]]:
    return [(i, j) for i in range(rank) for j in range(i, rank)]


def gram(name: str, fac: str, rank: int = 2) -> str:
    return f"{name} AS (SELECT {', '.join(f'sum(f{i} * f{j}) AS g{i}{j}' for i, j in pairs(rank))} FROM {fac})"


def system(name: str, obs: str, fac: str, rank: int = 2) -> str:
    sums = [f"sum(f{i} * f{j}) AS a{i}{j}" for i, j in pairs(rank)] + [f"sum(y * f{i}) AS b{i}" for i in range(rank)]
    return f"{name} AS (SELECT row_id, {', '.join(sums)}, count(*) AS n FROM {obs} JOIN {fac} ON col_id = id GROUP BY row_id)"


def ridge(name: str, sys: str, gram_name: str, reg: float = REG, weight: float = UNOBSERVED, rank: int = 2) -> str:
    cells = [f"a{i}{j} + {weight}::double * g{i}{j} + {reg if i == j else 0.0}::double AS a{i}{j}" for i, j in pairs(rank)]
    return f"{name} AS (SELECT row_id, {', '.join(cells)}, {', '.join(f'b{i}' for i in range(rank))} FROM {sys}, {gram_name})"


def solved2(name: str, sys: str) -> str:
    return f"{name} AS (SELECT row_id AS id, (a11 * b0 - a01 * b1) / (a00 * a11 - a01 * a01) AS f0, (a00 * b1 - a01 * b0) / (a00 * a11 - a01 * a01) AS f1 FROM {sys})"


def refit(name: str, obs: str, fac: str, reg: float = REG, weight: float = UNOBSERVED) -> str:
    """CTEs that end in the refitted side ``name``."""
    return ", ".join([gram(f"{name}_g", fac), system(f"{name}_s", obs, fac), ridge(f"{name}_r", f"{name}_s", f"{name}_g", reg, weight), solved2(name, f"{name}_r")])


def loss(obs: str, rows: str, columns: str, reg: float = REG, weight: float = UNOBSERVED) -> str:
    """One row observed, all_cells, reg, total (not rounded)."""
    observed = f"(SELECT sum((y - s) * (y - s)) FROM (SELECT y, w.f0 * h.f0 + w.f1 * h.f1 AS s FROM {obs} JOIN {rows} w ON row_id = w.id JOIN {columns} h ON col_id = h.id))"
    cells = f"(SELECT a.x * b.x + 2 * a.xy * b.xy + a.yy * b.yy FROM (SELECT sum(f0 * f0) AS x, sum(f0 * f1) AS xy, sum(f1 * f1) AS yy FROM {rows}) a, (SELECT sum(f0 * f0) AS x, sum(f0 * f1) AS xy, sum(f1 * f1) AS yy FROM {columns}) b)"
    norms = f"((SELECT sum(f0 * f0 + f1 * f1) FROM {rows}) + (SELECT sum(f0 * f0 + f1 * f1) FROM {columns}))"
    return f"SELECT observed, all_cells, reg, observed + all_cells + reg AS total FROM (SELECT {observed} AS observed, {weight}::double * {cells} AS all_cells, {reg}::double * {norms} AS reg)"


def rounded(columns: list[str], digits: int = 6) -> str:
    return ", ".join(f"round({c}, {digits}) + 0.0 AS {c.split('.')[-1]}" for c in columns)


def bf16(x: str) -> str:
    return f"(({x}) * 35184372088833.0::double - (({x}) * 35184372088833.0::double - ({x})))"
