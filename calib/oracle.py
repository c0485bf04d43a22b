"""DuckDB SQL of the methods, with iterations unrolled into chained CTEs. Built apart from the Spark plans that it checks."""

from __future__ import annotations

D5 = 5
XS = ["x0", "x1", "x2", "x3", "x4"]


def num(v: float) -> str:
    return f"({float(v)!r}::DOUBLE)"


def line(label: str = "planted", blocks: int = 64) -> str:
    """CTE body of the line-item view."""
    flip = "CASE WHEN ('0x' || substr(h, 9, 8))::BIGINT % 100 < 5 THEN -1.0 ELSE 1.0 END"
    y = "CASE WHEN l_returnflag = 'R' THEN 1.0 ELSE -1.0 END" if label == "noise" else f"(CASE WHEN 0.0::DOUBLE + x0 * 1.0 + x1 * 0.5 + x2 * -0.75 + x3 * 0.25 > 0 THEN 1.0 ELSE -1.0 END) * ({flip})"
    return f"""(SELECT *, ({y})::DOUBLE AS y, ('0x' || substr(h, 1, 8))::BIGINT AS ord, (('0x' || substr(h, 1, 8))::BIGINT % {blocks})::INT AS blk FROM (
      SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_returnflag, l_linestatus, (l_quantity - 25.5::DOUBLE) / 14.43::DOUBLE AS x0, (l_extendedprice - 53000::DOUBLE) / 30000::DOUBLE AS x1,
             (l_discount - 0.05::DOUBLE) / 0.0316::DOUBLE AS x2, (l_tax - 0.04::DOUBLE) / 0.0258::DOUBLE AS x3, 1.0::DOUBLE AS x4,
             md5(concat_ws(':', l_orderkey, l_linenumber, l_partkey, l_suppkey, '0')) AS h FROM lineitem))"""


def dot(w: str = "w", d: int = D5) -> str:
    return " + ".join(f"x{j} * {w}{j}" for j in range(d))


def dot_values(w) -> str:
    return " + ".join(f"x{j} * {num(v)}" for j, v in enumerate(w))


def loss(kind: str, z: str) -> str:
    return {
        "svm": f"greatest(1 - y * ({z}), 0.0)",
        "lr": f"(greatest(-({z}) * y, 0.0) + ln(1 + exp(-abs(({z}) * y))))",
        "squared": f"((({z}) - y) * (({z}) - y) / 2)",
    }[kind]


def slope(kind: str, z: str) -> str:
    e = f"exp(-abs(({z}) * y))"
    return {
        "svm": f"(CASE WHEN 1 - y * ({z}) > 0 THEN -y ELSE 0.0 END)",
        "lr": f"(-y * (CASE WHEN ({z}) * y >= 0 THEN {e} / (1 + {e}) ELSE 1 / (1 + {e}) END))",
        "squared": f"(({z}) - y)",
    }[kind]


def sums(kind: str, source: str, group: str = "", d: int = D5) -> str:
    """SELECT of n, f and g0.. over rows with x0.., y and w0.."""
    z = dot("w", d)
    inner = f"SELECT {group + ', ' if group else ''}{', '.join(f'x{j}' for j in range(d))}, {loss(kind, z)} AS f, {slope(kind, z)} AS g FROM {source}"
    return f"SELECT {group + ', ' if group else ''}count(*) AS n, sum(f) AS f, {', '.join(f'sum(g * x{j}) AS g{j}' for j in range(d))} FROM ({inner})" + (f" GROUP BY {group}" if group else "")


def ws(w: str = "w", d: int = D5, digits: int | None = 6) -> str:
    return ", ".join(f"round({w}{j}, {digits}) + 0.0 AS w{j}" if digits is not None else f"{w}{j}" for j in range(d))


def bgd(kind: str, steps: list[float], label: str = "planted", tag: str = "", extra: str = "") -> str:
    """k, loss, w0.. of plain descent with the given steps."""
    ctes = [f"ex AS {line(label)}", "v0 AS (SELECT " + ", ".join(f"0.0::DOUBLE AS w{j}" for j in range(D5)) + ")"]
    out = []
    for k in range(len(steps) + 1):
        ctes.append(f"m{k} AS ({sums(kind, f'ex, v{k}')})")
        out.append(f"SELECT {extra}{k} AS k, round(f, 4) AS loss, {ws()} FROM v{k}, m{k}")
        if k < len(steps):
            ctes.append(f"v{k + 1} AS (SELECT " + ", ".join(f"w{j} - {num(steps[k])} * g{j} AS w{j}" for j in range(D5)) + f" FROM v{k}, m{k})")
    return "WITH " + ",\n".join(ctes) + "\n" + "\nUNION ALL ".join(out)


def significant(v: str) -> str:
    return f"format('{{:.8e}}', {v})::DOUBLE"


def spec_bgd(kind: str, grids: list[list[float]], what: str = "trace", label: str = "planted") -> str:
    """Speculative descent over a grid of steps for each iteration. what: trace or candidates."""
    ctes = [f"ex AS {line(label)}", "v0 AS (SELECT " + ", ".join(f"0.0::DOUBLE AS w{j}" for j in range(D5)) + ")", f"b0 AS (SELECT v0.*, m.* FROM v0, ({sums(kind, 'ex, v0')}) m)"]
    out = []
    for k, grid in enumerate(grids, 1):
        values = ", ".join(f"({i}, {num(a)})" for i, a in enumerate(grid))
        ctes.append(f"c{k} AS (SELECT t.i AS i, t.alpha AS alpha, " + ", ".join(f"w{j} - t.alpha * g{j} AS w{j}" for j in range(D5)) + f" FROM b{k - 1}, (VALUES {values}) t(i, alpha))")
        ctes.append(f"m{k} AS ({sums(kind, f'ex, c{k}', 'i')})")
        ctes.append(f"b{k} AS (SELECT c{k}.*, m{k}.* EXCLUDE (i) FROM c{k} JOIN m{k} USING (i) ORDER BY {significant('f')}, i LIMIT 1)")
        if what == "trace":
            out.append(f"SELECT {k} AS k, {len(grid)} AS s, i::INT AS best, alpha, round(f, 4) AS loss, {ws()} FROM b{k}")
        else:
            out.append(f"SELECT {k} AS k, i::INT AS i, alpha, round(f, 4) AS loss FROM m{k} JOIN c{k} USING (i)")
    return "WITH " + ",\n".join(ctes) + "\n" + "\nUNION ALL ".join(out)


def fold(alpha: str, source: str, group: str = "", kind: str = "svm", batch: int = 1) -> str:
    """w after one ordered pass of single steps over `source` (x0.., y and the start in w0..), by group."""
    z = " + ".join(f"r.x{j} * a.x{j}" for j in range(D5))
    g = slope(kind, z).replace("y", "r.y")
    acc = "{" + ", ".join(f"'x{j}': a.x{j} - {alpha} * ({g}) * r.x{j}" for j in range(D5)) + ", 'y': 0.0::DOUBLE}"
    row = "{" + ", ".join(f"'x{j}': x{j}" for j in range(D5)) + ", 'y': y}"
    start = "{" + ", ".join(f"'x{j}': any_value(w{j})" for j in range(D5)) + ", 'y': 0.0::DOUBLE}"
    lists = f"SELECT {group + ', ' if group else ''}count(*) AS n, list({row} ORDER BY ord, l_orderkey, l_linenumber, l_partkey, l_suppkey) AS l, {start} AS s FROM {source}" + (f" GROUP BY {group}" if group else "")
    keep = f"{group}, " if group else ""
    return f"SELECT {keep}n, " + ", ".join(f"r.x{j} AS w{j}" for j in range(D5)) + f" FROM (SELECT {keep}n, list_reduce(l, lambda a, r: {acc}, s) AS r FROM ({lists}))"


def fold_late(alpha: str, source: str, late: int, kind: str = "svm") -> str:
    """fold() of all rows with updates that read the model of late - 1 updates ago. The state holds the last models, a0.. the oldest."""
    names = [f"{chr(97 + k)}{j}" for k in range(late) for j in range(D5)]
    z = " + ".join(f"r.a{j} * a.a{j}" for j in range(D5))
    g, new = slope(kind, z).replace("y", "r.y"), chr(96 + late)
    moved = [f"'{n}': " + (f"a.{n} - {alpha} * ({g}) * r.a{n[1:]}" if n[0] == new else f"a.{chr(ord(n[0]) + 1)}{n[1:]}") for n in names]
    row = ", ".join(f"'{n}': " + (f"x{n[1:]}" if n[0] == "a" else "0.0::DOUBLE") for n in names)
    start = ", ".join(f"'{n}': any_value(w{n[1:]})" for n in names)
    lists = f"SELECT count(*) AS n, list({{{row}, 'y': y}} ORDER BY ord, l_orderkey, l_linenumber, l_partkey, l_suppkey) AS l, {{{start}, 'y': 0.0::DOUBLE}} AS s FROM {source}"
    return "SELECT n, " + ", ".join(f"r.{new}{j} AS w{j}" for j in range(D5)) + f" FROM (SELECT n, list_reduce(l, lambda a, r: {{{', '.join(moved)}, 'y': 0.0::DOUBLE}}, s) AS r FROM ({lists}))"


def zeros() -> str:
    return "(SELECT " + ", ".join(f"0.0::DOUBLE AS w{j}" for j in range(D5)) + ")"


def estimates(n: str, s1: str, s2: str, total: str, z: float = 1.0) -> dict[str, str]:
    var = f"(CASE WHEN {n} > 1 THEN greatest(0.0, {s2} - {s1} * {s1} / {n}) / ({n} - 1) ELSE 0.0 END)"
    est = f"({total} * 1.0::DOUBLE / {n} * {s1})"
    std = f"({total} * sqrt({var} / {n} * greatest(0.0, 1 - {n} * 1.0::DOUBLE / {total})))"
    return {"est": est, "std": std, "low": f"({est} - {z} * {std})", "high": f"({est} + {z} * {std})", "rel_err": f"(CASE WHEN {std} = 0 THEN 0.0 WHEN {est} = 0 THEN 'inf'::DOUBLE ELSE 2 * {z} * {std} / abs({est}) END)"}
