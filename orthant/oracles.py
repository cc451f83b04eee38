"""SQL of the small forms, unrolled, as DuckDB runs it on the same tables. Used to check, never to compute."""

from __future__ import annotations

M = 2147483647
MATRIX = {
    "x_img": "SELECT row_key, col_key, value FROM quantized WHERE value > 0",
    "x_split": "SELECT vec_id AS row_key, CAST(c + CASE WHEN v < 0 THEN 64 ELSE 0 END AS BIGINT) AS col_key, abs(v) AS value FROM cells WHERE v <> 0",
    "x_cust": "SELECT o_custkey AS row_key, CAST(kind AS BIGINT) AS col_key, sum(l_quantity) AS value FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN (SELECT p_brand AS b, p_type AS t, row_number() OVER (ORDER BY p_brand, p_type) - 1 AS kind FROM (SELECT DISTINCT p_brand, p_type FROM part) u) k ON p_brand = b AND p_type = t GROUP BY 1, 2",
    "x_part": "SELECT l_partkey AS row_key, l_suppkey AS col_key, sum(l_quantity) AS value FROM lineitem GROUP BY 1, 2",
    "x_evt": "SELECT user_id AS row_key, CAST(CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END * 24 + extract(hour FROM ts) AS BIGINT) AS col_key, CAST(count(*) AS DOUBLE) AS value FROM events GROUP BY 1, 2",
    "x_ship": "SELECT l_suppkey AS row_key, CAST(extract(year FROM l_shipdate) * 12 + extract(month FROM l_shipdate) AS BIGINT) AS col_key, sum(l_extendedprice) AS value FROM lineitem GROUP BY 1, 2",
    "x_shipf": "SELECT l_suppkey AS row_key, CAST((extract(year FROM l_shipdate) * 12 + extract(month FROM l_shipdate)) * 3 + CASE l_returnflag WHEN 'A' THEN 0 WHEN 'N' THEN 1 ELSE 2 END AS BIGINT) AS col_key, sum(l_extendedprice) AS value FROM lineitem GROUP BY 1, 2",
    "x_big": "SELECT o_custkey AS row_key, l_partkey AS col_key, sum(l_quantity) AS value FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2",
}
_CELLS = "cells AS (SELECT vec_id, CAST(generate_subscripts(embedding, 1) - 1 AS BIGINT) AS c, CAST(unnest(embedding) AS DOUBLE) AS v FROM embeddings), quantized AS (SELECT vec_id AS row_key, c AS col_key, CAST(floor((v - (SELECT min(v) FROM cells)) / ((SELECT max(v) FROM cells) - (SELECT min(v) FROM cells)) * 255) AS DOUBLE) AS value FROM cells)"
TEXTS = {
    "x_doc": "SELECT doc_id AS row_key, text FROM documents ORDER BY doc_id LIMIT 5000",
    "x_pages": r"SELECT page_id AS row_key, regexp_replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '&[a-z]+;', ' ', 'g') AS text FROM pages",
    "x_conversations": "SELECT conv_id * 4 + CASE role WHEN 'assistant' THEN 0 WHEN 'system' THEN 1 WHEN 'user' THEN 2 ELSE 3 END AS row_key, text FROM conversations",
}


def vocabulary(name: str) -> str:
    return f"texts AS ({TEXTS[name]}), tokens AS (SELECT row_key, unnest(regexp_extract_all(lower(text), '[a-z]{{2,}}')) AS word FROM texts), vocab AS (SELECT word, n, CAST(row_number() OVER (ORDER BY n DESC, word) - 1 AS BIGINT) AS col_key FROM (SELECT word, count(*) AS n FROM tokens GROUP BY word ORDER BY n DESC, word LIMIT 1000) t)"


def matrix(name: str) -> str:
    """CTEs that end with x(row_key, col_key, value)."""
    if name in TEXTS:
        return f"{vocabulary(name)}, x AS (SELECT row_key, col_key, CAST(count(*) AS DOUBLE) AS value FROM tokens JOIN vocab USING (word) GROUP BY 1, 2)"
    head = f"{_CELLS}, " if name in ("x_img", "x_split") else ""
    return f"{head}x AS (SELECT row_key, col_key, CAST(value AS DOUBLE) AS value FROM ({MATRIX[name]}) m WHERE value <> 0)"


def uniform(key: str, stream: int, seed: int) -> str:
    u = f"(({key} % {M}) * 48271 + {stream * 16807 + seed * 69621 + 12345}) % {M}"
    for c in (11, 101, 1009):
        u = f"(({u}) * ({u}) + ({key} % {M}) + {c}) % {M}"
    return f"((CAST(({u}) AS DOUBLE) + 0.5) / 2147483647.0::DOUBLE)"


def normal(key: str, j: int, seed: int) -> str:
    return f"(sqrt(-2.0::DOUBLE * ln({uniform(key, 2 * j, seed)})) * cos(6.283185307179586::DOUBLE * {uniform(key, 2 * j + 1, seed)}))"


def f_list(k: int, form: str = "f{j}") -> str:
    return ", ".join(form.format(j=j) for j in range(k))


def start(name: str, side: str, k: int, seed: int, scale: str = "1.0::DOUBLE") -> str:
    return f"{name} AS (SELECT key, " + ", ".join(f"{uniform('key', j, seed)} * {scale} AS f{j}" for j in range(k)) + f" FROM (SELECT DISTINCT {side}_key AS key FROM x) q)"


def gaussian(name: str, side: str, s: int, seed: int) -> str:
    return f"{name} AS (SELECT key, " + ", ".join(f"{normal('key', j, seed)} AS f{j}" for j in range(s)) + f" FROM (SELECT DISTINCT {side}_key AS key FROM x) q)"


def times(name: str, factor: str, k: int, side: str = "row") -> str:
    """X B for side row, X' A for side col."""
    other = "col" if side == "row" else "row"
    return f"{name} AS (SELECT x.{side}_key AS key, " + ", ".join(f"sum(x.value * t.f{j}) AS f{j}" for j in range(k)) + f" FROM x JOIN {factor} t ON x.{other}_key = t.key GROUP BY 1)"


def gram(name: str, factor: str, k: int) -> str:
    return f"{name} AS (SELECT " + ", ".join(f"sum(f{min(i, j)} * f{max(i, j)}) AS g{i}_{j}" for i in range(k) for j in range(k)) + f" FROM {factor})"


def cross(name: str, left: str, s: int, right: str, k: int) -> str:
    return f"{name} AS (SELECT " + ", ".join(f"sum(l.f{i} * r.f{j}) AS c{i}_{j}" for i in range(s) for j in range(k)) + f" FROM {left} l JOIN {right} r ON l.key = r.key)"


def small_product(name: str, factor: str, s: int, c: str, k: int) -> str:
    return f"{name} AS (SELECT key, " + ", ".join(" + ".join(f"f{i} * c{i}_{j}" for i in range(s)) + f" AS f{j}" for j in range(k)) + f" FROM {factor}, {c})"


def small_gram(name: str, c: str, s: int, k: int) -> str:
    return f"{name} AS (SELECT " + ", ".join(" + ".join(f"c{m}_{i} * c{m}_{j}" for m in range(s)) + f" AS g{i}_{j}" for i in range(k) for j in range(k)) + f" FROM {c})"


def sweep(name: str, f: str, h: str, g: str, k: int, alpha: float = 0.0, beta: float = 0.0, only: int | None = None) -> str:
    """A chain of CTEs, one per component."""
    g_cols = ", ".join(f"g{i}_{j}" for i in range(k) for j in range(k))
    out = [f"{name}_s AS (SELECT f.key, {f_list(k, 'f.f{j}')}, {f_list(k, 'coalesce(h.f{j}, 0) AS h{j}')}, {g_cols} FROM {f} f LEFT JOIN {h} h ON f.key = h.key, {g})"]
    last = f"{name}_s"
    for j in range(k) if only is None else (only,):
        fg = " + ".join(f"f{i} * g{i}_{j}" for i in range(k))
        new = f"CASE WHEN g{j}_{j} > 1e-12 THEN greatest(h{j} - ({fg}) + f{j} * g{j}_{j} - {alpha}::DOUBLE, 0) / (g{j}_{j} + {beta}::DOUBLE) ELSE f{j} END"
        out.append(f"{name}_{j} AS (SELECT key, " + ", ".join(f"{new} AS f{i}" if i == j else f"f{i}" for i in range(k)) + f", {f_list(k, 'h{j}')}, {g_cols} FROM {last})")
        last = f"{name}_{j}"
    return ", ".join([*out, f"{name} AS (SELECT key, {f_list(k)} FROM {last})"])


def pointwise(name: str, f: str, h: str, g: str, k: int, form) -> str:
    """One expression per component from h, g and the old f."""
    return f"{name} AS (SELECT f.key, " + ", ".join(f"{form(j)} AS f{j}" for j in range(k)) + f" FROM {f} f LEFT JOIN (SELECT key AS hk, {f_list(k, 'f{j} AS h{j}')} FROM {h}) h ON f.key = h.hk, {g})"


def fg(k: int, j: int, part: str = "{x}") -> str:
    return " + ".join(f"f{i} * " + part.format(x=f"g{i}_{j}") for i in range(k))


def mu_form(k: int):
    return lambda j: f"f{j} * greatest(coalesce(h{j}, 0), 0) / ({fg(k, j)} + 1e-12)"


def signed_form(k: int):
    return lambda j: f"f{j} * sqrt((greatest(coalesce(h{j}, 0), 0) + {fg(k, j, 'greatest(-({x}), 0)')}) / (greatest(-coalesce(h{j}, 0), 0) + {fg(k, j, 'greatest({x}, 0)')} + 1e-12))"


def als_form(k: int):
    """k = 2, by the explicit inverse."""
    ridge = "(1e-10 * (g0_0 + g1_1) / 2 + 1e-12)"
    a, d, b = f"(g0_0 + {ridge})", f"(g1_1 + {ridge})", "g0_1"
    return lambda j: f"greatest((coalesce(h{j}, 0) * {d if j == 0 else a} - coalesce(h{1 - j}, 0) * {b}) / ({a} * {d} - {b} * {b}), 0)"


def pgd_form(k: int):
    length = "((g0_0 + g1_1) / 2 + sqrt(((g0_0 - g1_1) / 2) * ((g0_0 - g1_1) / 2) + g0_1 * g0_1))"
    return lambda j: f"greatest(f{j} - ({fg(k, j)} - coalesce(h{j}, 0)) / {length}, 0)"


def gradient_form(k: int):
    return lambda j: f"{fg(k, j)} - coalesce(h{j}, 0)"


def normalise(name_f: str, name_o: str, f: str, o: str, k: int) -> str:
    size = ", ".join(f"CASE WHEN sum(f{j} * f{j}) > 0 THEN sqrt(sum(f{j} * f{j})) ELSE 1.0 END AS n{j}" for j in range(k))
    return f"{name_f}_n AS (SELECT {size} FROM {f}), {name_f} AS (SELECT key, {f_list(k, 'f{j} / n{j} AS f{j}')} FROM {f}, {name_f}_n), {name_o} AS (SELECT key, {f_list(k, 'f{j} * n{j} AS f{j}')} FROM {o}, {name_f}_n)"


def orthonormal(name: str, y: str, s: int) -> str:
    """Columns one after another: earlier directions are taken off twice, then the rest is scaled."""
    out, last = [], y
    for j in range(s):
        for turn in range(2 if j else 0):
            dots = ", ".join(f"sum(f{i} * f{j}) AS d{i}" for i in range(j))
            now = f"{name}_{j}_{turn}"
            out.append(f"{now}d AS (SELECT {dots} FROM {last})")
            out.append(f"{now} AS (SELECT key, " + ", ".join(f"f{i} - (" + " + ".join(f"d{m} * f{m}" for m in range(j)) + f") AS f{i}" if i == j else f"f{i}" for i in range(s)) + f" FROM {last}, {now}d)")
            last = now
        now = f"{name}_{j}"
        out.append(f"{now} AS (SELECT key, " + ", ".join(f"f{i} / (SELECT sqrt(sum(f{j} * f{j})) FROM {last}) AS f{i}" if i == j else f"f{i}" for i in range(s)) + f" FROM {last})")
        last = now
    return ", ".join([*out, f"{name} AS (SELECT key, {f_list(s)} FROM {last})"])


def rounded(source: str, k: int, digits: int = 5, side: str | None = None) -> str:
    tag = f"'{side}' AS side, " if side else ""
    return f"SELECT {tag}key, {f_list(k, 'round(f{j}, ' + str(digits) + ') AS f{j}')} FROM {source}"


def query(*ctes: str, select: str) -> str:
    return "WITH " + ",\n".join(ctes).replace(" AS (SELECT", " AS MATERIALIZED (SELECT") + "\n" + select
