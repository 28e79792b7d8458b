"""Point specifications of the given tables and the fixed instances that queries and their SQL twins share."""

from __future__ import annotations

import random
from typing import NamedTuple

from pyspark.sql import DataFrame, SparkSession

from balclust.functions import points as P
from balclust.functions.points import Dimension, PointSpec
from balclust.plans import params as params_

_LINE_ORDER = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate")
_DAYS, _DAYS_SQL = "datediff(cast(o_orderdate as date), date '1995-01-01')", "date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE))"
_SECOND = "hour(ts) * 3600 + minute(ts) * 60 + cast(second(ts) as int)"
_LINES, _LINES_SQL = "length(text) - length(replace(text, '\\n', '')) + 1", "length(text) - length(replace(text, chr(10), '')) + 1"


def projection(row: int, seed: int = 7) -> Dimension:
    """A sum of the embedding's entries with random signs, in whole millionths."""
    rng = random.Random(f"projection {seed} {row}")
    signs = [rng.choice("+-") for _ in range(64)]
    # One small expression, however many entries: a sum written out would be repeated in each step of the hashes.
    spark = f"aggregate(zip_with(embedding, array({', '.join(f'{s}1L' for s in signs)}), (e, s) -> cast(round(e * 1e6) as bigint) * s), 0L, (a, b) -> a + b)"
    sql = " ".join(f"{s} CAST(round(embedding[{k + 1}] * 1e6) AS BIGINT)" for k, s in enumerate(signs))
    return Dimension(f"{spark} / 1e6", -6, 6, f"(0 {sql}) / 1e6")


LI2 = PointSpec("li2", "lineitem", (Dimension("l_quantity", 1, 50), Dimension("l_extendedprice", 900, 105000)), 10, order=_LINE_ORDER)
LI4 = PointSpec("li4", "lineitem", (*LI2.dimensions, Dimension("l_discount", 0, 0.1), Dimension("l_tax", 0, 0.08)), 8, order=_LINE_ORDER)
ORD = PointSpec("ord", "orders", (Dimension("o_totalprice", 0, 500000), Dimension(_DAYS, 0, 2500, _DAYS_SQL)), 10, key="o_orderkey")
CUST = PointSpec("cust", "customer", (Dimension("c_acctbal", -1000, 10000),), 10, key="c_custkey")
CUSTG = PointSpec("custg", "customer", (Dimension("c_acctbal", -1000, 10000), Dimension("c_nationkey", 0, 24)), 8, key="c_custkey")
EV12 = PointSpec("ev12", "events", (Dimension("value", 0, 600), Dimension(_SECOND, 0, 86399)), 12, key="event_id")
EV10 = PointSpec("ev10", "events", EV12.dimensions, 10, key="event_id")
EMB = PointSpec("emb", "embeddings", tuple(projection(m) for m in range(4)), 8, key="vec_id")
SUP = PointSpec("sup", "supplier", (Dimension("s_acctbal", -1000, 10000), Dimension("s_nationkey", 0, 24)), 6, key="s_suppkey")
DOC = PointSpec("doc", "documents", (Dimension("sqrt(n_chars)", 0, 400), Dimension(_LINES, 1, 512, _LINES_SQL)), 8, key="doc_id")
WEB = PointSpec("web", "pages", (Dimension("length(html)", 0, 65536), Dimension("length(url)", 0, 256)), 8, key="page_id")
CONV = PointSpec("conv", "conversations", (Dimension("turn", 0, 15), Dimension("length(text)", 0, 2048)), 8, order=("conv_id", "turn"))


class Instance(NamedTuple):
    """A specification with its grid, hashes and parameters, all fixed."""

    spec: PointSpec
    params: params_.Params
    grid: P.Grid
    cell_hash: P.Hash
    part_hash: P.Hash
    core_hash: P.Hash
    centres: tuple[tuple[int, ...], ...]


def instance(spec: PointSpec, k: int, r: float, guess: float, profile: str = "calibrated", seed: int = 11, **options) -> Instance:
    p = params_.derive(k, r, spec.d, spec.levels, guess, profile=profile, **options)
    own = f"{spec.name} {seed}"
    independence = min(8, p.independence)
    rng = random.Random(f"centres {own}")
    centres = tuple(tuple(rng.randint(1, spec.side) for _ in range(spec.d)) for _ in range(k))
    return Instance(spec, p, P.grid(spec.d, spec.levels, own), *(P.hash_family(own, f, independence) for f in ("cells", "parts", "core")), centres)


W01 = instance(LI2, 8, 2, 2.0**27)
W02 = instance(LI2, 8, 1, 2.0**22)
W03 = instance(LI4, 8, 2, 2.0**25)
W04 = instance(ORD, 2, 2, 2.0**29)
W05 = instance(CUST, 2, 2, 2.0**25)
W06 = instance(EV12, 4, 2, 2.0**30)
W07 = instance(EV10, 4, 2, 2.0**26)
W11 = instance(EMB, 10, 2, 2.0**17)
W13 = instance(SUP, 2, 2, 2.0**8)
W14 = instance(DOC, 4, 2, 2.0**16)
W15 = instance(WEB, 4, 2, 2.0**14)
W15C = instance(CONV, 4, 2, 2.0**15)
W16 = instance(CUSTG, 5, 2, 2.0**20)
W20 = instance(LI2, 8, 2, 16.0, profile="theory")
ALL = {"w01": W01, "w02": W02, "w03": W03, "w04": W04, "w05": W05, "w06": W06, "w07": W07, "w11": W11, "w13": W13, "w14": W14, "w15": W15, "w15c": W15C, "w16": W16, "w20": W20}


def load(spark: SparkSession, sf_dir: str, spec: PointSpec, keep: tuple[str, ...] = ()) -> DataFrame:
    """The tagged points of a specification."""
    return P.points(spark.read.parquet(f"{sf_dir}/{spec.table}.parquet"), spec, keep)
