"""SQL twins of the summary's steps, for an engine without our code: chains of common table expressions with literals of a fixed instance."""

from __future__ import annotations

from balclust.functions.points import FIELD, RANGE, Hash, PointSpec, Poly
from balclust.operators.coreset import rates
from balclust.plans.params import Params
from balclust.workloads import Instance


def lattice(spec: PointSpec, m: int) -> str:
    d = spec.dimensions[m]
    return f"CAST(least({spec.side}, greatest(1, CAST(floor((CAST({d.sql or d.expression} AS DOUBLE) - {d.low}) / ({d.high} - {d.low}) * {spec.side - 1}) AS BIGINT) + 1)) AS BIGINT)"


def points(spec: PointSpec, keep: tuple[str, ...] = ()) -> str:
    """pts: tag, x0.., kept columns."""
    xs = ", ".join(f"{lattice(spec, m)} AS x{m}" for m in range(spec.d))
    kept = "".join(f", {c}" for c in keep)
    if spec.key:
        return f"pts AS (SELECT CAST({spec.key} AS BIGINT) AS tag, {xs}{kept} FROM {spec.table})"
    order = ", ".join(spec.order)
    return f"raw AS (SELECT {order}, {xs} FROM {spec.table}), pts AS (SELECT row_number() OVER (PARTITION BY {', '.join(spec.coordinates)} ORDER BY {order}) AS tag, {', '.join(spec.coordinates)}{kept} FROM raw)"


def leaves(i: Instance) -> str:
    keys = ", ".join(f"x{m} - {u} + {i.spec.side} AS c{m}" for m, u in enumerate(i.grid.shift))
    return f"leaf AS (SELECT *, {keys} FROM pts)"


def cells(i: Instance) -> str:
    keys = ", ".join(f"c{m} >> ({i.spec.levels} - lvl) AS k{m}" for m in range(i.spec.d))
    names = ", ".join(f"k{m}" for m in range(i.spec.d))
    return f"cells AS (SELECT lvl AS level, {keys}, count(*) AS n FROM leaf, (SELECT CAST(unnest(range(-1, {i.spec.levels + 1})) AS INTEGER) AS lvl) GROUP BY lvl, {names})"


def number(v: float) -> str:
    """A literal that SQL reads with the type it has here; without an exponent it would be a decimal."""
    return repr(v) if isinstance(v, int) or "e" in repr(v) else f"{v!r}e0"


def case(column: str, values: dict) -> str:
    return f"CASE {column} " + " ".join(f"WHEN {k} THEN {number(v)}" for k, v in values.items()) + " END"


def limits(p: Params) -> str:
    return case("level", {i: p.cell_threshold(i) for i in range(-1, p.levels + 1)})


def heavy(i: Instance) -> str:
    return f"heavy AS (SELECT * FROM cells WHERE level < {i.spec.levels} AND n >= {limits(i.params)})"


def route(i: Instance) -> str:
    """routed: points with level and part."""
    on = " AND ".join(f"h.k{m} = l.c{m} >> ({i.spec.levels} - h.level)" for m in range(i.spec.d))
    names = ", ".join(f"c{m}" for m in range(i.spec.d))
    parents = ", ".join(f"leaf.c{m} >> ({i.spec.levels} - level + 1) AS p{m}" for m in range(i.spec.d))
    return f"""deepest AS (SELECT {', '.join(f'l.c{m}' for m in range(i.spec.d))}, CAST(max(h.level) + 1 AS INTEGER) AS level FROM (SELECT DISTINCT {names} FROM leaf) l JOIN heavy h ON {on} GROUP BY ALL),
routed AS (SELECT leaf.*, level, {parents} FROM leaf JOIN deepest USING ({names}))"""


def part_key(i: Instance) -> str:
    return ", ".join(["level", *(f"p{m}" for m in range(i.spec.d))])


def parts(i: Instance) -> str:
    return f"parts AS (SELECT {part_key(i)}, count(*) AS size FROM routed GROUP BY {part_key(i)})"


def important(i: Instance) -> str:
    return f"important AS (SELECT * FROM parts WHERE size >= {case('level', {j: i.params.gamma * i.params.cell_threshold(j) for j in range(i.spec.levels + 1)})})"


def poly(p: Poly, columns: list[str], point: str) -> tuple[str, str]:
    """(the folded point, the polynomial of a column that holds it)."""
    fold = f"({columns[0]} % {FIELD})"
    for c in columns[1:]:
        fold = f"(({fold} * {p.fold} + {c}) % {FIELD})"
    acc = f"CAST({p.coefficients[0]} AS BIGINT)"
    for c in p.coefficients[1:]:
        acc = f"(({acc} * {point} + {c}) % {FIELD})"
    return fold, acc


def hashed(i: Instance, h: Hash, source: str, name: str) -> str:
    """name: source with h, the pair of both polynomials as one number."""
    (fold1, acc1), (fold2, acc2) = (poly(p, ["tag", *i.spec.coordinates], pt) for p, pt in zip(h, ("pt1", "pt2"), strict=True))
    return f"{name}_pt AS (SELECT *, {fold1} AS pt1, {fold2} AS pt2 FROM {source}), {name} AS (SELECT * EXCLUDE (pt1, pt2), {acc1} * {FIELD} + {acc2} AS h FROM {name}_pt)"


def coreset(i: Instance) -> str:
    cut = rates(i.params)
    return f"{hashed(i, i.core_hash, 'routed', 'hashed')}, core AS (SELECT hashed.*, size, {case('level', {j: RANGE / t for j, t in cut.items()})} AS w FROM hashed JOIN important USING ({part_key(i)}) WHERE h < {case('level', cut)})"


def chain(i: Instance, *steps: str) -> str:
    """WITH the steps named, in the order they need each other."""
    known = {"points": lambda i: points(i.spec), "leaves": leaves, "cells": cells, "heavy": heavy, "route": route, "parts": parts, "important": important, "coreset": coreset}
    return "WITH " + ",\n".join(known[s](i) for s in steps) + "\n"


UP_TO_PARTS = ("points", "leaves", "cells", "heavy", "route", "parts")
UP_TO_CORESET = (*UP_TO_PARTS, "important", "coreset")


def dist(coordinates: list[str], z: tuple[int, ...], r: float) -> str:
    sq = " + ".join(f"({x} - {c}) * ({x} - {c})" for x, c in zip(coordinates, z, strict=True))
    if r == 2:
        return f"CAST({sq} AS BIGINT)"
    square = f"CAST({sq} AS DOUBLE)"
    factors = [square] * int(r // 2) + [f"sqrt({square})"] * (int(2 * r) % 4 // 2) + [f"sqrt(sqrt({square}))"] * (int(2 * r) % 2)
    return f"CAST(round({' * '.join(factors)} * 1000000) AS BIGINT)"
