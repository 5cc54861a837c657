"""Relations built from the given tables, as SQL that Spark and DuckDB both run."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from linform.functions.semirings import BOOLEAN, COUNT, Semiring
from linform.operators.relation import AnnotatedRelation, keys_of
from linform.sources.tables import table

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings")


@dataclass(frozen=True)
class Fixture:
    arity: int
    spark: str
    duck: str


def _both(arity: int, sql: str) -> Fixture:
    """sql: {days:c:d}, {hours:c:t}, {json:c:k} stand for what the dialects write differently."""

    def one(engine: str) -> str:
        def put(m: re.Match) -> str:
            kind, a, b = m[1], m[2], m[3]
            if kind == "days":
                return f"cast(datediff({a}, date'{b}') as bigint)" if engine == "spark" else f"date_diff('day', date '{b}', cast({a} as date))"
            if kind == "hours":
                return f"timestampdiff(HOUR, timestamp_ntz'{b} 00:00:00', {a})" if engine == "spark" else f"date_diff('hour', timestamp '{b} 00:00:00', {a})"
            return f"cast(get_json_object({a}, '$.{b}') as bigint)" if engine == "spark" else f"cast(json_extract({a}, '$.{b}') as bigint)"

        return re.sub(r"\{(\w+):(\w+):([\w-]+)\}", put, sql)

    return Fixture(arity, one("spark"), one("duck"))


def _counted(keys: list[str], source: str, where: str = "") -> Fixture:
    cols = ", ".join(f"cast({k} as bigint) AS c{i}" for i, k in enumerate(keys))
    return _both(len(keys), f"SELECT {cols}, count(*) AS ann FROM {source}{' WHERE ' + where if where else ''} GROUP BY {', '.join(str(i + 1) for i in range(len(keys)))}")


def _literal(rows: list[tuple]) -> Fixture:
    n = len(rows[0]) - 1
    cols = ", ".join(f"cast(c{i} as bigint) AS c{i}" for i in range(n))
    names = ", ".join([*keys_of(n), "ann"])
    return _both(n, f"SELECT {cols}, cast(ann as bigint) AS ann FROM (VALUES {', '.join(map(str, rows))}) AS t({names})")


def _generated(n: int, selects: list[str], arity: int) -> Fixture:
    """Rows made from the numbers i below n, without a table. selects: c0, c1, ... as SQL over i, a set of rows each."""
    cols = ", ".join(f"cast(c{k} as bigint) AS c{k}" for k in range(arity))
    made = lambda numbers: f"SELECT DISTINCT {cols}, cast(1 as bigint) AS ann FROM (" + " UNION ALL ".join(f"SELECT {x} FROM {numbers}" for x in selects) + ") AS t"
    return Fixture(arity, made(f"(SELECT id AS i FROM range({n})) AS r"), made(f"(SELECT range AS i FROM range({n})) AS r"))


def cents(c: str) -> str:
    return f"round({c} * 100)"


# Weights of 3x3 kernels on offsets -1..1 (zeros omitted).
KERNELS = {
    "blur": {(-1, -1): 1, (-1, 0): 2, (-1, 1): 1, (0, -1): 2, (0, 0): 4, (0, 1): 2, (1, -1): 1, (1, 0): 2, (1, 1): 1},
    "sobel_x": {(-1, -1): -1, (-1, 1): 1, (0, -1): -2, (0, 1): 2, (1, -1): -1, (1, 1): 1},
    "sobel_y": {(-1, -1): -1, (-1, 0): -2, (-1, 1): -1, (1, -1): 1, (1, 0): 2, (1, 1): 1},
    "laplace": {(-1, 0): 1, (0, -1): 1, (0, 0): -4, (0, 1): 1, (1, 0): 1},
}
KERNEL_HOURS = 24
#: Numbers of a hub.
HUB = 3_000

_EMB8 = (
    "SELECT cast(vec_id as bigint) AS c0, cast(floor(pos / 8) as bigint) AS c1, cast(pos % 8 as bigint) AS c2, cast(round(cast(x as double) * 10000) as bigint) AS ann FROM (SELECT vec_id, posexplode(embedding) AS (pos, x) FROM embeddings) AS t",
    "SELECT cast(vec_id as bigint) AS c0, cast(floor((pos - 1) / 8) as bigint) AS c1, cast((pos - 1) % 8 as bigint) AS c2, cast(round(cast(x as double) * 10000) as bigint) AS ann FROM (SELECT vec_id, unnest(embedding) AS x, generate_subscripts(embedding, 1) AS pos FROM embeddings) AS t",
)
_CHANNELS = "SELECT cast(floor(c0 / 4) as bigint) AS c0, c0 % 4 AS c1, c1 AS c2, c2 AS c3, ann FROM ({}) AS e"

FIXTURES: dict[str, Fixture] = {
    "sup_cents": _counted([cents("s_acctbal")], "supplier"),
    "cus_cents": _counted([cents("c_acctbal")], "customer"),
    "ord_cents": _counted([cents("o_totalprice")], "orders"),
    "day_min_urgent": _both(1, "SELECT {days:o_orderdate:1995-01-01} AS c0, cast(min(round(o_totalprice * 100)) as bigint) AS ann FROM orders WHERE o_orderpriority = '1-URGENT' GROUP BY 1"),
    "day_min_low": _both(1, "SELECT {days:o_orderdate:1995-01-01} AS c0, cast(min(round(o_totalprice * 100)) as bigint) AS ann FROM orders WHERE o_orderpriority = '5-LOW' GROUP BY 1"),
    "hour_sig": _both(1, "SELECT {hours:ts:2024-01-01} AS c0, cast(sum(cast(round(value * 100) as bigint)) as bigint) AS ann FROM events GROUP BY 1"),
    "kern24": _literal([(t, KERNEL_HOURS - t) for t in range(KERNEL_HOURS)]),
    "user_k": _both(2, "SELECT user_id AS c0, {json:props:k} AS c1, count(*) AS ann FROM events GROUP BY 1, 2"),
    "img_sq": _counted(["l_suppkey", "l_quantity"], "lineitem"),
    "emb8": Fixture(3, *_EMB8),
    **{f"kern_{n}": _literal([(*k, w) for k, w in ws.items()]) for n, ws in KERNELS.items()},
    "kern_all": _literal([(f, *k, w) for f, ws in enumerate(KERNELS.values()) for k, w in ws.items()]),
    "skew_a": _counted(["l_suppkey", "l_quantity"], "lineitem"),
    "skew_b": _counted(["l_quantity", "l_suppkey"], "lineitem", "l_returnflag = 'A'"),
    "skew_c": _counted(["l_partkey % 150", "floor(l_partkey / 20) + l_linenumber"], "lineitem"),
    "sup_part": _counted(["l_suppkey", "l_partkey"], "lineitem"),
    "part_cus": _counted(["l_partkey", "o_custkey"], "lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "sup_cus": _counted(["l_suppkey", "o_custkey"], "lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "li_order": _counted(["l_suppkey", "l_orderkey"], "lineitem"),
    "order_cus": _counted(["o_orderkey", "o_custkey"], "orders"),
    "size": _counted(["p_size"], "part"),
    "qty": _counted(["l_quantity"], "lineitem"),
    "disc": _counted([cents("l_discount")], "lineitem"),
    "tax": _counted([cents("l_tax")], "lineitem"),
    "line": _counted(["l_linenumber"], "lineitem"),
    "region_key": _counted(["r_regionkey"], "region"),
    "nation_key": _counted(["n_nationkey"], "nation"),
    "sup_qty_line": _counted(["l_suppkey", "l_quantity", "l_linenumber"], "lineitem"),
    "wedge": _both(3, "SELECT cast(l_suppkey % 20 as bigint) AS c0, cast(l_partkey % 20 as bigint) AS c1, cast((sum(l_linenumber) + cast(sum(l_quantity) as bigint)) % 11 - 5 as bigint) AS c2, cast(1 as bigint) AS ann FROM lineitem GROUP BY 1, 2"),
    "mod7": _counted(["l_suppkey % 7", "l_partkey % 7"], "lineitem"),
    "mod7b": _counted(["l_orderkey % 7", "l_linenumber % 7"], "lineitem"),
    "mod4": _counted(["l_suppkey % 4", "l_partkey % 4"], "lineitem"),
    "mod4b": _counted(["l_orderkey % 4", "l_linenumber % 4"], "lineitem"),
    **{f"len_{x}": _counted(["n_chars"], "documents", f"lang = '{x}'") for x in ("en", "fr", "de", "es")},
    "mod2": _counted(["l_suppkey % 2", "l_partkey % 2"], "lineitem"),
    "mod2b": _counted(["l_orderkey % 2", "l_linenumber % 2"], "lineitem"),
    # hubs of HUB numbers, for the triangle and (in the coordinates X+Y, Y, Y+Z) for the skew triangle
    "hub": _generated(HUB, ["0 AS c0, i AS c1", "i AS c0, 0 AS c1"], 2),
    "hub_a": _generated(HUB, ["-i AS c0, i AS c1", "i AS c0, 0 AS c1"], 2),
    "hub_b": _generated(HUB, ["0 AS c0, i AS c1", "i AS c0, -i AS c1"], 2),
    # batches of four matrices as channels, and a layer of two filters over them
    "emb8c": Fixture(4, *(_CHANNELS.format(x) for x in _EMB8)),
    "kern_layer": _literal([(f, c, *at, w * (f + 1)) for f in range(2) for c in range(4) for at, w in list(KERNELS.values())[(f + c) % 4].items()]),
    "bag_a": _literal([(1, 1), (2, 3), (3, 4), (4, 5)]),
    "bag_b": _literal([(-1, 0, 1), (0, -1, 5), (0, 1, 3)]),
    # the bag example on lineitem; annotations stay small, so that sums of their products stay in 64 bits at any size
    "bag_line": _both(1, "SELECT cast(l_linenumber as bigint) AS c0, count(*) % 1000 + 1 AS ann FROM lineitem GROUP BY 1"),
    "bag_step": _both(2, "SELECT cast(l_suppkey % 3 - 1 as bigint) AS c0, cast(l_partkey % 3 - 1 as bigint) AS c1, count(*) % 1000 + 1 AS ann FROM lineitem GROUP BY 1, 2"),
    "_zero": _literal([(0, 1)]),
}


def frame(spark: SparkSession, sf_dir: str, name: str):
    """The fixture as a frame c0, ..., ann."""
    sql = FIXTURES[name].spark
    used = [t for t in TABLES if re.search(rf"(FROM|JOIN) {t}\b", sql)]
    for t in used:
        sql = re.sub(rf"(FROM|JOIN) {t}\b", rf"\1 {{{t}}}", sql)
    return spark.sql(sql, **{t: table(spark, sf_dir, t) for t in used})


def relation(spark: SparkSession, sf_dir: str, name: str, semiring: Semiring = COUNT, units: bool = False) -> AnnotatedRelation:
    """units: annotations replaced by the semiring's one."""
    f = FIXTURES[name]
    df = frame(spark, sf_dir, name).where(" and ".join(f"{k} is not null" for k in keys_of(f.arity)))
    ann = semiring.one() if units or semiring is BOOLEAN else F.col("ann").cast(semiring.kind)
    return AnnotatedRelation(df.select(*keys_of(f.arity), ann.alias("ann")), f.arity, semiring)
