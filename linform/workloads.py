"""The worked examples as workloads on the given tables: queries by evaluator, and the same in SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linform import experiments
from linform.functions import semirings as S
from linform.functions.fields import ExtensionField, PrimeField, Q
from linform.operators import evaluate as E
from linform.operators import reducts, relational, tensor
from linform.operators.relation import AnnotatedRelation, Database
from linform.plans import planner, trees
from linform.plans.query import UNIT, ConstrainedQuery, constraints_as_atoms, constraints_eliminated, parse_query
from linform.plans.sqlapi import where_sql
from linform.sources import fixtures, shared, tables
from linform.sources.fixtures import FIXTURES, relation

SUM = "CAST(sum({product}) AS BIGINT)"
DECIMAL = "CAST(sum(CAST({product} AS HUGEINT)) AS DECIMAL(38,0))"


@dataclass(frozen=True)
class Workload:
    text: str
    atoms: dict[str, str]
    semiring: S.Semiring = S.COUNT
    ann: str = SUM
    evaluators: tuple[str, ...] = ("sparse",)
    field: object = Q
    units: bool = False
    #: Applied to the answer, as SQL for both sides.
    having: str = ""

    def query(self):
        return parse_query(self.text, self.field)

    def database(self, spark: SparkSession, sf_dir: str) -> Database:
        return Database({a: relation(spark, sf_dir, f, self.semiring, self.units) for a, f in self.atoms.items()}, self.semiring, self.field)

    def run(self, spark: SparkSession, sf_dir: str, evaluator: str = "") -> DataFrame:
        q = self.query()
        db = reducts.trimmed(q, self.database(spark, sf_dir))
        if self.semiring == S.MAX_TIMES:  # products of four counts leave 64 bits as tables grow
            db = planner.widened_sums(q, db)
        if evaluator in ("", "auto"):
            out = planner.evaluate(q, db)
        elif evaluator.startswith("sparse_"):
            out = E.eval_sparse(q, db, join=evaluator.removeprefix("sparse_"))
        elif evaluator == "integral":
            out = E.eval_sparse(q, db, weights=[1, 1] + [0] * (len(q.atoms) - 2))
        elif evaluator.startswith("plain_"):
            out = E.eval_plain(q, db, join=evaluator.removeprefix("plain_"))
        else:
            out = E.EVALUATORS[evaluator](q, db)
        return out.where(self.having) if self.having else out

    def sql(self, by_hand: str | None = None) -> str:
        """by_hand: the SELECT as somebody wrote it, instead of the one that the query's equations give."""
        q = self.query()
        with_ = ", ".join(f"f_{f} AS ({FIXTURES[f].duck})" for f in dict.fromkeys(self.atoms.values()))
        modulus = self.field.p if self.field.characteristic else None
        sql = f"WITH {with_} " + (by_hand or where_sql(q, {a: f"f_{f}" for a, f in self.atoms.items()}, self.ann, modulus))
        sums = self.semiring in (S.COUNT, S.BIG_COUNT)
        if q.head and sums:
            sql = f"SELECT * FROM ({sql}) AS answer WHERE ann <> 0"
        elif sums:
            sql = f"SELECT coalesce(ann, 0) AS ann FROM ({sql}) AS answer"
        return f"SELECT * FROM ({sql}) AS answer WHERE {self.having}" if self.having else sql


_SKEW = {"A": "skew_a", "B": "skew_b", "C": "skew_c"}
_TRIANGLE = {"R": "sup_part", "S": "part_cus", "T": "sup_cus"}
_QUAD = {"A": "tax", "B": "disc", "C": "qty", "D": "size"}
_FIVE = {"R1": "skew_c", "R2": "mod7", "R3": "mod7b", "R4": "user_k", "R5": "skew_c"}
_BIG = dict(semiring=S.BIG_COUNT, ann=DECIMAL)
_MIN_PLUS = dict(semiring=S.MIN_PLUS, ann="CAST(min({plus}) AS BIGINT)")
_EXISTS = dict(semiring=S.BOOLEAN, ann="count(*) > 0")

WORKLOADS: dict[str, Workload] = {
    "threesum_count": Workload("Q() <- A(X)*B(Y)*C(X+Y)", {"A": "sup_cents", "B": "cus_cents", "C": "ord_cents"}, evaluators=("dense", "sparse", "value", "domain", "size", "joined", "where")),
    "threesum_exists": Workload("Q() <- A(X)*B(Y)*C(X+Y)", {"A": "sup_cents", "B": "cus_cents", "C": "ord_cents"}, **_EXISTS, evaluators=("sparse", "domain")),
    "threesum_self": Workload("Q() <- A(X)*A(Y)*B(X+Y)", {"A": "sup_cents", "B": "cus_cents"}, evaluators=("sparse", "size", "where", "inequalities", "bruteforce")),
    "minconv_days": Workload("Q(T+S) <- A(T)*B(S)", {"A": "day_min_urgent", "B": "day_min_low"}, **_MIN_PLUS, evaluators=("dense", "joined")),
    "conv1d_hours": Workload("Q(T+K) <- A(T)*P(K)", {"A": "hour_sig", "P": "kern24"}, evaluators=("dense", "sparse", "value", "joined")),
    "autocorr_hours": Workload("Q(L) <- A(T)*A(T+L)", {"A": "hour_sig"}, having="h0 between 0 and 168", evaluators=("dense", "joined")),
    "conv2d_counts": Workload("Q(I,J) <- A(I+L,J+K)*P(L,K)", {"A": "img_sq", "P": "kern_sobel_x"}, evaluators=("sparse", "joined")),
    "conv2d_blur": Workload("Q(I,J) <- A(I+L,J+K)*P(L,K)", {"A": "img_sq", "P": "kern_blur"}, evaluators=("sparse", "joined")),
    "conv2d_laplace": Workload("Q(I,J) <- A(I+L,J+K)*P(L,K)", {"A": "img_sq", "P": "kern_laplace"}, evaluators=("grid",)),
    "conv2d_sobel_y": Workload("Q(I,J) <- A(I+L,J+K)*P(L,K)", {"A": "img_sq", "P": "kern_sobel_y"}),
    "conv2d_batch": Workload("Q(V,I,J) <- A(V,I+L,J+K)*P(L,K)", {"A": "emb8", "P": "kern_sobel_x"}, evaluators=("joined",)),
    "conv_layer": Workload("Q(V,F,I,J) <- A(V,I+L,J+K)*P(F,L,K)", {"A": "emb8", "P": "kern_all"}, evaluators=("joined",)),
    "conv_channels": Workload("Q(V,F,I,J) <- A(V,C,I+L,J+K)*P(F,C,L,K)", {"A": "emb8c", "P": "kern_layer"}, evaluators=("joined",)),
    "skew_triangle": Workload("Q(X,Y,Z) <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)", _SKEW, evaluators=("sparse", "sparse_hypercube", "sparse_hypercube_frames", "sparse_binary", "integral", "inequality_bags", "dense", "domain", "size", "joined")),
    "skew_triangle_exists": Workload("Q() <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)", _SKEW, **_EXISTS, evaluators=("sparse",)),
    "hub_triangle": Workload("Q(X,Y,Z) <- R(X,Y)*S(Y,Z)*T(X,Z)", {"R": "hub", "S": "hub", "T": "hub"}, evaluators=("plain_levelwise", "sparse_hypercube")),
    "hub_skew": Workload("Q(X,Y,Z) <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)", {"A": "hub_a", "B": "hub_b", "C": "hub"}, evaluators=("sparse", "sparse_hypercube", "inequality_bags")),
    "twopath": Workload("Q() <- R(X,Y)*S(Y,Z)", {"R": "li_order", "S": "order_cus"}, evaluators=("size", "unguarded", "joined")),
    "twopath_parts": Workload("Q() <- R(X,Y)*S(Y,Z)", {"R": "sup_part", "S": "part_cus"}, evaluators=("size", "unguarded")),
    "matmul": Workload("Q(X,Z) <- R(X,Y)*S(Y,Z)", {"R": "sup_part", "S": "part_cus"}, evaluators=("sparse", "plain_binary", "joined")),
    "triangle": Workload("Q(X,Y,Z) <- R(X,Y)*S(Y,Z)*T(X,Z)", _TRIANGLE, evaluators=("plain_levelwise", "plain_hypercube", "plain_binary", "sparse")),
    "linear_guard": Workload("Q() <- R(X,Y)*S(Y,X+Y)", {"R": "user_k", "S": "skew_b"}, evaluators=("sparse", "size", "joined", "where", "inequality_bags")),
    "quad_tree": Workload("Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)", _QUAD, **_BIG, evaluators=("dense", "value", "domain", "size", "unguarded", "where")),
    "quad_tree_min": Workload("Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)", _QUAD, **_MIN_PLUS, evaluators=("value", "size")),
    "quad_tree_max": Workload("Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)", _QUAD, semiring=S.MAX_PLUS, ann="CAST(max({plus}) AS BIGINT)", evaluators=("domain",)),
    "quad_tree_product": Workload("Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)", _QUAD, semiring=S.MAX_TIMES, ann="CAST(max({product}) AS BIGINT)", evaluators=("size",)),
    "quad_tree_bottleneck": Workload("Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)", _QUAD, semiring=S.BOTTLENECK, ann="CAST(max(least({each})) AS BIGINT)", evaluators=("domain",)),
    "quad_tree_real": Workload("Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)", _QUAD, semiring=S.REAL, units=True, ann="CAST(count(*) AS DOUBLE)", evaluators=("value", "domain")),
    "quad_tree_set": Workload("Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)", _QUAD, semiring=S.BOOLEAN, ann="count(*) > 0", evaluators=("domain",)),
    "quad_tree_mod": Workload("Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)", _QUAD, semiring=S.modular(7), ann="CAST(sum({product}) % 7 AS BIGINT)", having="ann <> 0", evaluators=("size",)),
    "ksum_docs": Workload("Q() <- A(X)*B(Y)*S(X+Y)", {"A": "len_en", "B": "len_fr", "S": "len_de"}, evaluators=("value", "domain", "size", "unguarded")),
    "ksum3": Workload("Q() <- A(X)*B(Y)*C(Z)*S(X+Y+Z)", {"A": "tax", "B": "disc", "C": "line", "S": "qty"}, units=True, ann="CAST(count(*) AS BIGINT)", evaluators=("value", "domain", "size", "unguarded")),
    "ksum4": Workload("Q() <- A(A)*B(B)*C(C)*D(D)*S(A+B+C+D)", {"A": "tax", "B": "disc", "C": "line", "D": "qty", "S": "size"}, **_BIG, evaluators=("value", "domain", "size", "unguarded")),
    "ksum5": Workload("Q() <- A(A)*B(B)*C(C)*D(D)*E(E)*S(A+B+C+D+E)", {"A": "tax", "B": "disc", "C": "line", "D": "qty", "E": "region_key", "S": "size"}, **_BIG, evaluators=("value", "domain", "unguarded")),
    "five_atoms": Workload("Q(Y+Z) <- R1(W+X,X+Y)*R2(W,X)*R3(X,Y)*R4(Y,Z)*R5(X+Y,Y+Z)", _FIVE, evaluators=("size", "joined")),
    "sum_equality5": Workload("Q() <- R1(A)*R2(B)*R3(C)*R4(D)*R5(A+B+C-D)", {"R1": "region_key", "R2": "nation_key", "R3": "line", "R4": "disc", "R5": "tax"}, **_BIG, evaluators=("domain", "size", "where")),
    "gf7_conv": Workload("Q(A+B) <- M(A,C)*N(A+C,B)", {"M": "mod7", "N": "mod7b"}, field=PrimeField(7), evaluators=("dense", "grid", "value", "sparse", "joined")),
    "gf2_conv": Workload("Q(A+B) <- M(A,C)*N(A+C,B)", {"M": "mod2", "N": "mod2b"}, field=PrimeField(2), evaluators=("grid", "value", "sparse")),
    "exact_path4": Workload("Q() <- E(A,B,X)*E(B,C,Y)*E(C,D,-X-Y)", {"E": "wedge"}, **_EXISTS, evaluators=("size", "joined")),
    "exact_path4_count": Workload("Q() <- E(A,B,X)*E(B,C,Y)*E(C,D,-X-Y)", {"E": "wedge"}, evaluators=("size", "sparse", "joined")),
    "bag_example": Workload("Q(2X+2Z) <- A(X)*B(Y-X,Z-Y)*C(Z)", {"A": "bag_line", "B": "bag_step", "C": "bag_line"}, evaluators=tuple(E.EVALUATORS)),
    "bag_example_subst": Workload("Q(4U+2V+2W) <- A(U)*B(V,W)*C(U+V+W)", {"A": "bag_a", "B": "bag_b", "C": "bag_a"}, evaluators=("dense", "sparse", "bruteforce")),
    "degenerate_sum": Workload("Q() <- R(X+Y)", {"R": "ord_cents"}, evaluators=("sparse", "dense")),
    "rational_scaling": Workload("Q(X+Y) <- A(X)*B(Y)*C(1/2X+1/3Y)", {"A": "disc", "B": "tax", "C": "qty"}, evaluators=("dense", "value", "size", "where")),
}


# ---- SQL written by hand from the examples, for workloads whose equations the library would otherwise supply ------

_3SUM = "FROM f_sup_cents a, f_cus_cents b, f_ord_cents c WHERE c.c0 = a.c0 + b.c0"
_CONV2D = "SELECT a.c0 - p.c0 AS h0, a.c1 - p.c1 AS h1, CAST(sum(a.ann * p.ann) AS BIGINT) AS ann FROM f_img_sq a, f_kern_{} p GROUP BY ALL"
_QUAD_SQL = "SELECT a.c0 + b.c0 AS h0, {} AS ann FROM f_tax a, f_disc b, f_qty c, f_size d WHERE d.c0 - c.c0 = a.c0 + b.c0 GROUP BY 1"
_ABCD = "a.ann * b.ann * c.ann * d.ann"
_PATH4 = "FROM f_wedge x, f_wedge y, f_wedge z WHERE x.c1 = y.c0 AND y.c1 = z.c0 AND x.c2 + y.c2 + z.c2 = 0"
BY_HAND = {
    "threesum_count": f"SELECT CAST(sum(a.ann * b.ann * c.ann) AS BIGINT) AS ann {_3SUM}",
    "threesum_exists": f"SELECT count(*) > 0 AS ann {_3SUM}",
    "threesum_self": "SELECT CAST(sum(a.ann * b.ann * c.ann) AS BIGINT) AS ann FROM f_sup_cents a, f_sup_cents b, f_cus_cents c WHERE c.c0 = a.c0 + b.c0",
    "minconv_days": "SELECT a.c0 + b.c0 AS h0, CAST(min(a.ann + b.ann) AS BIGINT) AS ann FROM f_day_min_urgent a, f_day_min_low b GROUP BY 1",
    "conv1d_hours": "SELECT a.c0 + p.c0 AS h0, CAST(sum(a.ann * p.ann) AS BIGINT) AS ann FROM f_hour_sig a, f_kern24 p GROUP BY 1",
    "autocorr_hours": "SELECT b.c0 - a.c0 AS h0, CAST(sum(a.ann * b.ann) AS BIGINT) AS ann FROM f_hour_sig a, f_hour_sig b GROUP BY 1",
    "conv2d_counts": _CONV2D.format("sobel_x"),
    **{f"conv2d_{k}": _CONV2D.format(k) for k in ("blur", "laplace", "sobel_y")},
    "conv2d_batch": "SELECT a.c0 AS h0, a.c1 - p.c0 AS h1, a.c2 - p.c1 AS h2, CAST(sum(a.ann * p.ann) AS BIGINT) AS ann FROM f_emb8 a, f_kern_sobel_x p GROUP BY ALL",
    "conv_layer": "SELECT a.c0 AS h0, p.c0 AS h1, a.c1 - p.c1 AS h2, a.c2 - p.c2 AS h3, CAST(sum(a.ann * p.ann) AS BIGINT) AS ann FROM f_emb8 a, f_kern_all p GROUP BY ALL",
    "conv_channels": "SELECT a.c0 AS h0, p.c0 AS h1, a.c2 - p.c2 AS h2, a.c3 - p.c3 AS h3, CAST(sum(a.ann * p.ann) AS BIGINT) AS ann FROM f_emb8c a JOIN f_kern_layer p ON a.c1 = p.c1 GROUP BY ALL",
    "skew_triangle": "SELECT a.c0 AS h0, a.c1 AS h1, b.c1 AS h2, CAST(a.ann * b.ann * c.ann AS BIGINT) AS ann FROM f_skew_a a JOIN f_skew_b b ON a.c1 = b.c0 JOIN f_skew_c c ON c.c0 = a.c0 + a.c1 AND c.c1 = b.c0 + b.c1",
    "hub_triangle": "SELECT r.c0 AS h0, r.c1 AS h1, s.c1 AS h2, CAST(1 AS BIGINT) AS ann FROM f_hub r JOIN f_hub t ON r.c0 = t.c0 JOIN f_hub s ON s.c0 = r.c1 AND s.c1 = t.c1",
    "hub_skew": "SELECT a.c0 AS h0, a.c1 AS h1, b.c1 AS h2, CAST(1 AS BIGINT) AS ann FROM f_hub_a a JOIN f_hub c ON c.c0 = a.c0 + a.c1 JOIN f_hub_b b ON b.c0 = a.c1 AND b.c1 = c.c1 - a.c1",
    "twopath": "SELECT CAST(sum(r.ann * s.ann) AS BIGINT) AS ann FROM f_li_order r JOIN f_order_cus s ON r.c1 = s.c0",
    "matmul": "SELECT r.c0 AS h0, s.c1 AS h1, CAST(sum(r.ann * s.ann) AS BIGINT) AS ann FROM f_sup_part r JOIN f_part_cus s ON r.c1 = s.c0 GROUP BY ALL",
    "triangle": "SELECT r.c0 AS h0, r.c1 AS h1, s.c1 AS h2, CAST(r.ann * s.ann * t.ann AS BIGINT) AS ann FROM f_sup_part r JOIN f_part_cus s ON r.c1 = s.c0 JOIN f_sup_cus t ON t.c0 = r.c0 AND t.c1 = s.c1",
    "linear_guard": "SELECT CAST(sum(r.ann * s.ann) AS BIGINT) AS ann FROM f_user_k r JOIN f_skew_b s ON s.c0 = r.c1 AND s.c1 = r.c0 + r.c1",
    "quad_tree": _QUAD_SQL.format(f"CAST(sum(CAST({_ABCD} AS HUGEINT)) AS DECIMAL(38,0))"),
    "quad_tree_min": _QUAD_SQL.format(f"CAST(min({_ABCD.replace(' * ', ' + ')}) AS BIGINT)"),
    "quad_tree_max": _QUAD_SQL.format(f"CAST(max({_ABCD.replace(' * ', ' + ')}) AS BIGINT)"),
    "quad_tree_product": _QUAD_SQL.format(f"CAST(max({_ABCD}) AS BIGINT)"),
    "quad_tree_bottleneck": _QUAD_SQL.format("CAST(max(least(a.ann, b.ann, c.ann, d.ann)) AS BIGINT)"),
    "quad_tree_real": _QUAD_SQL.format("CAST(count(*) AS DOUBLE)"),
    "ksum_docs": "SELECT CAST(sum(a.ann * b.ann * s.ann) AS BIGINT) AS ann FROM f_len_en a, f_len_fr b, f_len_de s WHERE s.c0 = a.c0 + b.c0",
    "ksum3": "SELECT CAST(count(*) AS BIGINT) AS ann FROM f_tax a, f_disc b, f_line c, f_qty s WHERE s.c0 = a.c0 + b.c0 + c.c0",
    "ksum5": "SELECT CAST(sum(CAST(a.ann AS HUGEINT) * b.ann * c.ann * d.ann * e.ann * s.ann) AS DECIMAL(38,0)) AS ann FROM f_tax a, f_disc b, f_line c, f_qty d, f_region_key e, f_size s WHERE s.c0 = a.c0 + b.c0 + c.c0 + d.c0 + e.c0",
    "sum_equality5": "SELECT CAST(sum(CAST(a.ann AS HUGEINT) * b.ann * c.ann * d.ann * e.ann) AS DECIMAL(38,0)) AS ann FROM f_region_key a, f_nation_key b, f_line c, f_disc d, f_tax e WHERE a.c0 + b.c0 = d.c0 + e.c0 - c.c0",
    "gf7_conv": "SELECT (m.c0 + n.c1) % 7 AS h0, CAST(sum(m.ann * n.ann) AS BIGINT) AS ann FROM f_mod7 m JOIN f_mod7b n ON n.c0 = (m.c0 + m.c1) % 7 GROUP BY 1",
    "gf2_conv": "SELECT CAST(xor(m.c0, n.c1) AS BIGINT) AS h0, CAST(sum(m.ann * n.ann) AS BIGINT) AS ann FROM f_mod2 m JOIN f_mod2b n ON n.c0 = xor(m.c0, m.c1) GROUP BY 1",
    "exact_path4": f"SELECT count(*) > 0 AS ann {_PATH4}",
    "exact_path4_count": f"SELECT CAST(count(*) AS BIGINT) AS ann {_PATH4}",
    "bag_example": "SELECT 2 * (a.c0 + c.c0) AS h0, CAST(sum(a.ann * b.ann * c.ann) AS BIGINT) AS ann FROM f_bag_line a, f_bag_line c, f_bag_step b WHERE b.c0 + b.c1 = c.c0 - a.c0 GROUP BY 1",
    "degenerate_sum": "SELECT CAST(sum(ann) AS BIGINT) AS ann FROM f_ord_cents",
}


# ---- single queries -----------------------------------------------------------------------------------------


def _constrained(spark: SparkSession, sf_dir: str, name: str, how) -> DataFrame:
    """linear_guard and sum_equality5 as plain queries with equations."""
    if name == "linear_guard":
        plain, atoms = "Q() <- R(X,Y)*S(Y,Z)", {"R": "user_k", "S": "skew_b"}
        equation = {"X": 1, "Y": 1, "Z": -1}
    else:
        plain, atoms = "Q() <- R1(A)*R2(B)*R3(C)*R4(D)*R5(E)", WORKLOADS[name].atoms
        equation = {"A": 1, "B": 1, "C": 1, "D": -1, "E": -1}
    q = parse_query(plain)
    q = how(ConstrainedQuery(q, (tuple(Q.of(equation[v]) for v in q.variables),)))
    semiring = WORKLOADS[name].semiring
    return planner.evaluate(q, Database({a: relation(spark, sf_dir, f, semiring) for a, f in {**atoms, UNIT: "_zero"}.items()}, semiring))


def reduct_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The reduct of R(X+Y, Y, Z+W) onto X and X-Y."""
    q = parse_query("Q() <- R(X+Y,Y,Z+W)")
    x, y = (tuple(Q.of(int(v == w)) for w in q.variables) for v in "XY")
    minus = tuple(a - b for a, b in zip(x, y, strict=True))
    return reducts.reduct(relation(spark, sf_dir, "sup_qty_line"), q.atoms[0].forms, [x, minus], ["r0", "r1"], Q)


def measure_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exponents of the worked examples, computed from the query texts."""
    rows = [(n, int(m["k"]), *(float(m[x]) for x in ("rho", "dim_width", "vec_width", "frac_width"))) for n, m in ((n, planner.measures(parse_query(t))) for n, (t, *_) in EXPONENTS.items())]
    return spark.createDataFrame(rows, "name string, k int, rho double, dim_width double, vec_width double, frac_width double")


# Dimension, cover number and the three widths of the worked examples.
EXPONENTS = {
    "skew_triangle": ("Q(X,Y,Z) <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)", 3, 1.5, 2.0, 2.0, 1.5),
    "linear_guard": ("Q() <- R(X,Y)*S(Y,X+Y)", 2, 1.0, 1.0, 1.0, 1.0),
    "quad_tree": ("Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)", 3, 3.0, 1.0, 1.0, 2.0),
    "ksum2": ("Q() <- A(X)*B(Y)*S(X+Y)", 2, 2.0, 1.0, 1.0, 2.0),
    "ksum3": ("Q() <- A(X)*B(Y)*C(Z)*S(X+Y+Z)", 3, 3.0, 1.0, 1.0, 2.0),
    "ksum4": ("Q() <- A(X)*B(Y)*C(Z)*D(W)*S(X+Y+Z+W)", 4, 4.0, 1.0, 2.0, 3.0),
    "ksum5": ("Q() <- A(X)*B(Y)*C(Z)*D(W)*E(V)*S(X+Y+Z+W+V)", 5, 5.0, 1.0, 2.0, 3.0),
    "five_atoms": ("Q(Y+Z) <- R1(W+X,X+Y)*R2(W,X)*R3(X,Y)*R4(Y,Z)*R5(X+Y,Y+Z)", 4, 2.0, 2.0, 2.0, 1.5),
    "triangle": ("Q(X,Y,Z) <- R(X,Y)*S(Y,Z)*T(X,Z)", 3, 1.5, 2.0, 2.0, 1.5),
    "bag_example": ("Q(2X+2Z) <- A(X)*B(Y-X,Z-Y)*C(Z)", 3, 2.0, 1.0, 1.0, 2.0),
}

#: Values in each relation of the adversarial instances.
WIDE = (2, 3, 4)


def adversarial_messages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of each message of the sum chain on {j * n**(i-1)}, without guards and with those of vector covers; j are the
    residues modulo n of the part keys."""
    rows, part = [], tables.table(spark, sf_dir, "lineitem").select((F.col("l_partkey") % 12).alias("x")).distinct()
    part = shared.written(part, "residues")  # modulo each n below; the table is read once
    for n in WIDE:
        q, db = experiments.sum_instance(spark, 5, n, part.select((F.col("x") % n).alias("id")).distinct())
        tree = trees.sum_chain(q)
        for name, run in (("unguarded", E.eval_unguarded), ("domain", E.eval_by_domain)):
            run(q, db, tree, watch=lambda v, g, out, name=name, n=n: rows.append((n, name, v, out.count())) and None if v else None)
    return spark.createDataFrame(rows, "n int, method string, node int, message_rows long")


#: Part sums of the instances, by joins of the summands; with guards the last message holds only what a value of the sum leaves.
ADVERSARIAL_SQL = """
WITH c AS (SELECT DISTINCT n, l_partkey % n AS j FROM lineitem, (VALUES (2), (3), (4)) AS a(n)),
v AS (SELECT n, i, j * pow(n, i)::BIGINT AS x FROM c, range(5) AS b(i)),
two AS (SELECT DISTINCT a.n, a.x + b.x AS s FROM v a JOIN v b ON a.n = b.n AND a.i = 0 AND b.i = 1),
three AS (SELECT DISTINCT t.n, s + x AS s FROM two t JOIN v ON t.n = v.n AND i = 2),
four AS (SELECT DISTINCT t.n, s + x AS s FROM three t JOIN v ON t.n = v.n AND i = 3),
left_over AS (SELECT DISTINCT a.n, a.x - b.x AS s FROM v a JOIN v b ON a.n = b.n AND a.i = 0 AND b.i = 4),
counted AS (
SELECT n, 'unguarded' AS method, 3 AS node, count(*) AS message_rows FROM two GROUP BY n UNION ALL SELECT n, 'unguarded', 2, count(*) FROM three GROUP BY n
UNION ALL SELECT n, 'unguarded', 1, count(*) FROM four GROUP BY n UNION ALL SELECT n, 'domain', 3, count(*) FROM two GROUP BY n UNION ALL SELECT n, 'domain', 2, count(*) FROM three GROUP BY n
UNION ALL SELECT n, 'domain', 1, count(*) FROM four SEMI JOIN left_over USING (n, s) GROUP BY n)
SELECT CAST(n AS INTEGER) AS n, method, CAST(node AS INTEGER) AS node, message_rows FROM counted
"""


def growth(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that methods and baselines visit as instances grow."""
    return spark.createDataFrame(experiments.growth(spark), "workload string, instance string, method string, n long, size long, rows long")


def _reports(spark: SparkSession, sf_dir: str, columns: str) -> DataFrame:
    w = WORKLOADS["quad_tree"]
    q, db = w.query(), w.database(spark, sf_dir)
    rows = [[n, *(r[c.split()[0]] for c in columns.split(", "))] for n in ("domain", "size", "value") for r in planner.report(q, db, n)]
    return spark.createDataFrame(rows, f"method string, {columns}")


def query_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Guard rows beside their bound, and messages, for the query over four unary atoms."""
    return _reports(spark, sf_dir, "node int, cost string, guard_rows long, bound double, message_rows long, message_most long, most long")


def query_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds and bytes shuffled of the same runs; they differ from run to run."""
    return _reports(spark, sf_dir, "node int, seconds double, shuffle_bytes long")


#: Bags {X, Y} over A, B (root) and {Z-X-Y, Z} over C, D; the message is on X+Y, as differences of D and C. Sums of
#: joins are the root's answer. By size a bag's cover is both its atoms; by value the box of the largest value.
REPORT_SQL = """
a AS (SELECT c0 AS x FROM f_tax), b AS (SELECT c0 AS x FROM f_disc), c AS (SELECT c0 AS x FROM f_qty), d AS (SELECT c0 AS x FROM f_size),
n AS (SELECT (SELECT count(*) FROM a) * (SELECT count(*) FROM b) AS ab, (SELECT count(*) FROM c) * (SELECT count(*) FROM d) AS cd,
greatest((SELECT max(abs(x)) FROM a), (SELECT max(abs(x)) FROM b), (SELECT max(abs(x)) FROM c), (SELECT max(abs(x)) FROM d)) AS most),
m AS (SELECT count(DISTINCT d.x - c.x) AS r, max(abs(d.x - c.x)) AS w FROM c, d),
h AS (SELECT count(DISTINCT a.x + b.x) AS r, max(abs(a.x + b.x)) AS w FROM a, b WHERE EXISTS (SELECT 1 FROM c, d WHERE d.x - c.x = a.x + b.x))
SELECT method, CAST(node AS INTEGER) AS node, '2' AS cost, CASE node WHEN 0 THEN ab ELSE cd END AS guard_rows,
CAST(CASE WHEN method = 'value' THEN (2 * greatest(most, 1) + 1) ** 2 WHEN node = 0 THEN ab ELSE cd END AS DOUBLE) AS bound,
CASE node WHEN 0 THEN h.r ELSE m.r END AS message_rows, CASE node WHEN 0 THEN h.w ELSE m.w END AS message_most, most
FROM n, m, h, (VALUES ('domain'), ('size'), ('value')) AS x(method), (VALUES (0), (1)) AS y(node)
"""


def quad_tree_wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The four-atom query with a hundred times the counts: sizes tell that sums leave 64 bits, so 38 digits are taken."""
    w = WORKLOADS["quad_tree_min"]
    db = Database({a: relation(spark, sf_dir, f).scale(100) for a, f in w.atoms.items()})
    return planner.evaluate(w.query(), db, widen=True)


def gf16_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Elements of GF(16), all of them in GF(2): the grid has points of the least subfield only."""
    q = parse_query("Q(A+B) <- M(A,C)*N(A+C,B)", ExtensionField(2, 4))
    return E.eval_grid(q, Database({"M": relation(spark, sf_dir, "mod2"), "N": relation(spark, sf_dir, "mod2b")}, field=q.field))


def _sig(spark: SparkSession, d: str) -> AnnotatedRelation:
    return relation(spark, d, "hour_sig")


def _duck(*names: str) -> str:
    return "WITH " + ", ".join(f"f_{n} AS ({FIXTURES[n].duck})" for n in names) + " "


_TICKS = "SELECT user_id, CAST(floor(extract(epoch FROM ts)) AS BIGINT) AS t, event_id, event_type FROM events"


def _event_ticks(spark: SparkSession, d: str) -> DataFrame:
    at = F.timestamp_diff("SECOND", F.lit("1970-01-01 00:00:00").cast("timestamp_ntz"), F.col("ts"))
    return tables.table(spark, d, "events").select("user_id", at.alias("t"), "event_id", "event_type")


def _windows(spark: SparkSession, d: str, size: str, slide: str | None = None) -> DataFrame:
    got = tables.table(spark, d, "events").groupBy(F.window("ts", size, slide) if slide else F.window("ts", size), "event_type").agg(F.count("*").alias("n"))
    day = F.lit("1970-01-01 00:00:00").cast("timestamp_ntz")
    return got.select(F.timestamp_diff("SECOND", day, F.col("window.start")).alias("start"), "event_type", "n")


def _as_of(s: SparkSession, d: str) -> DataFrame:
    """Each event with the time of its user's latest purchase at or before it."""
    e = _event_ticks(s, d)
    right = e.where("event_type = 'purchase'").select("user_id", "t", F.col("t").alias("t_before"))
    return relational.as_of(e, right, "user_id", "t", "t_before").select("user_id", "t", "event_id", "t_before_as_of")


def threesum_witness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The least sum of three values with the values that make it: annotations carry costs and witnesses."""
    w, s = WORKLOADS["threesum_count"], S.witness("bigint")
    costs = F.struct(F.col("c0").alias("cost"), F.array("c0").alias("wit")).alias("ann")
    db = Database({a: AnnotatedRelation(fixtures.frame(spark, sf_dir, f).select("c0", costs), 1, s) for a, f in w.atoms.items()}, s)
    got = E.eval_sparse(w.query(), reducts.trimmed(w.query(), db), drop_zero=True)
    return got.select(F.col("ann.cost").alias("cost"), *(F.col("ann.wit")[i].alias(n) for i, n in enumerate("xyz")))


def gf4_conv(spark: SparkSession, sf_dir: str, run=E.eval_finite_field) -> DataFrame:
    """Sums of elements of GF(4), codes 0..3; the first element is multiplied by the field's generator (code 2)."""
    q = parse_query("Q(2A+B) <- M(A,C)*N(A+C,B)", ExtensionField(2, 2))
    return run(q, Database({"M": relation(spark, sf_dir, "mod4"), "N": relation(spark, sf_dir, "mod4b")}, field=q.field))


#: Codes of twice an element of GF(4), by its code.
_GF4_DOUBLE = "list_value(0, 2, 3, 1)"
_GF4_SQL = "SELECT CAST(xor({d}[m.c0 + 1], n.c1) AS BIGINT) AS h0, CAST(sum(m.ann * n.ann) AS BIGINT) AS ann FROM f_mod4 m JOIN f_mod4b n ON n.c0 = xor(m.c0, m.c1) GROUP BY 1"


SINGLE: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {
    "reduct_14": (reduct_example, _duck("sup_qty_line") + "SELECT DISTINCT c0 - c1 AS r0, c0 - 2 * c1 AS r1 FROM f_sup_qty_line"),
    "measures": (measure_table, "SELECT * FROM (VALUES " + ", ".join(f"('{n}', CAST({k} AS INTEGER), " + ", ".join(f"CAST({x} AS DOUBLE)" for x in rest) + ")" for n, (_, k, *rest) in EXPONENTS.items()) + ") AS t(name, k, rho, dim_width, vec_width, frac_width)"),
    "adversarial_messages": (adversarial_messages, ADVERSARIAL_SQL),
    "growth": (growth, experiments.growth_sql()),
    "query_report": (query_report, _duck("tax", "disc", "qty", "size").strip() + ", " + REPORT_SQL.strip()),
    "query_costs": (query_costs, None),
    "quad_tree_wide": (quad_tree_wide, f"SELECT h0, CAST(ann * 100000000 AS DECIMAL(38,0)) AS ann FROM ({WORKLOADS['quad_tree'].sql()}) AS t"),
    "gf16_bits__grid": (gf16_bits, _duck("mod2", "mod2b") + "SELECT CAST(xor(m.c0, n.c1) AS BIGINT) AS h0, CAST(sum(m.ann * n.ann) AS BIGINT) AS ann FROM f_mod2 m JOIN f_mod2b n ON n.c0 = xor(m.c0, m.c1) GROUP BY 1"),
    "conv2d_blur__tiled": (lambda s, d: tensor.convolve(relation(s, d, "img_sq"), relation(s, d, "kern_blur")), WORKLOADS["conv2d_blur"].sql(BY_HAND["conv2d_blur"])),
    "conv_layer__tiled": (lambda s, d: tensor.convolve(relation(s, d, "emb8"), relation(s, d, "kern_all"), shared=1, filters=1), WORKLOADS["conv_layer"].sql(BY_HAND["conv_layer"])),
    "conv_channels__tiled": (lambda s, d: tensor.convolve(relation(s, d, "emb8c"), relation(s, d, "kern_layer"), shared=1, filters=1, channels=1, tile=8), WORKLOADS["conv_channels"].sql(BY_HAND["conv_channels"])),
    "threesum_witness": (threesum_witness, _duck("sup_cents", "cus_cents", "ord_cents") + "SELECT a.c0 + b.c0 + c.c0 AS cost, a.c0 AS x, b.c0 AS y, c.c0 AS z FROM f_sup_cents a, f_cus_cents b, f_ord_cents c WHERE c.c0 = a.c0 + b.c0 ORDER BY 1, 2, 3, 4 LIMIT 1"),
    "gf4_conv": (gf4_conv, _duck("mod4", "mod4b") + _GF4_SQL.format(d=_GF4_DOUBLE)),
    "gf4_conv__grid": (lambda s, d: gf4_conv(s, d, E.eval_grid), _duck("mod4", "mod4b") + _GF4_SQL.format(d=_GF4_DOUBLE)),
    **{f"constraints_atoms__{n}": (lambda s, d, n=n: _constrained(s, d, n, constraints_as_atoms), WORKLOADS[n].sql(BY_HAND[n])) for n in ("linear_guard", "sum_equality5")},
    **{f"constraints_eliminated__{n}": (lambda s, d, n=n: _constrained(s, d, n, constraints_eliminated), WORKLOADS[n].sql(BY_HAND[n])) for n in ("linear_guard", "sum_equality5")},
    "relation_union": (lambda s, d: relation(s, d, "skew_a").union(relation(s, d, "skew_b").transpose([1, 0])).df, _duck("skew_a", "skew_b") + "SELECT c0, c1, CAST(sum(ann) AS BIGINT) AS ann FROM (SELECT c0, c1, ann FROM f_skew_a UNION ALL SELECT c1, c0, ann FROM f_skew_b) AS t GROUP BY 1, 2"),
    "relation_project": (lambda s, d: relation(s, d, "skew_a").project([[1, -2]]).df, _duck("skew_a") + "SELECT c0 - 2 * c1 AS c0, CAST(sum(ann) AS BIGINT) AS ann FROM f_skew_a GROUP BY 1"),
    "relation_restrict": (lambda s, d: relation(s, d, "sup_part").restrict(relation(s, d, "mod7").df.select("c0"), ["c0"]).df, _duck("sup_part") + "SELECT c0, c1, ann FROM f_sup_part WHERE c0 BETWEEN 0 AND 6"),
    "relation_scale_shift": (lambda s, d: relation(s, d, "qty").scale(3).shift([-7]).df, _duck("qty") + "SELECT c0 - 7 AS c0, 3 * ann AS ann FROM f_qty"),
    "relation_product": (lambda s, d: relation(s, d, "qty").product(relation(s, d, "tax")).df, _duck("qty", "tax") + "SELECT a.c0, b.c0 AS c1, a.ann * b.ann AS ann FROM f_qty a, f_tax b"),
    "common_support": (lambda s, d: relational.common_support(relation(s, d, "qty"), relation(s, d, "size")), _duck("qty", "size") + "SELECT c0 FROM f_qty INTERSECT SELECT c0 FROM f_size"),
    "result_difference": (lambda s, d: relational.difference(relation(s, d, "skew_a").df, relation(s, d, "skew_b").transpose([1, 0]).df), _duck("skew_a", "skew_b") + "SELECT c0, c1, ann, 'a' AS side FROM (SELECT * FROM f_skew_a EXCEPT SELECT c1, c0, ann FROM f_skew_b) AS x UNION ALL SELECT c0, c1, ann, 'b' FROM (SELECT c1 AS c0, c0 AS c1, ann FROM f_skew_b EXCEPT SELECT * FROM f_skew_a) AS y"),
    "result_equality": (lambda s, d: relational.difference(relation(s, d, "skew_a").df, relation(s, d, "img_sq").df).agg(F.count("*").alias("n")), "SELECT CAST(0 AS BIGINT) AS n"),
    "top_k": (lambda s, d: relational.top_k(WORKLOADS["conv1d_hours"].run(s, d, "sparse"), 10), f"SELECT * FROM ({WORKLOADS['conv1d_hours'].sql()}) AS a ORDER BY ann DESC, h0 LIMIT 10"),
    "top_k_per_supplier": (lambda s, d: relational.top_k_per(relation(s, d, "sup_part").df, ["c0"], 3), _duck("sup_part") + "SELECT c0, c1, ann FROM (SELECT *, row_number() OVER (PARTITION BY c0 ORDER BY ann DESC, c1) AS n FROM f_sup_part) AS t WHERE n <= 3"),
    "roll_up": (lambda s, d: relational.roll_up(relation(s, d, "mod7").df, ["c0", "c1"], F.sum("ann")), _duck("mod7") + "SELECT c0, c1, CAST(sum(ann) AS BIGINT) AS ann FROM f_mod7 GROUP BY ROLLUP (c0, c1)"),
    "cube": (lambda s, d: relational.cube(relation(s, d, "mod7").df, ["c0", "c1"], F.sum("ann")), _duck("mod7") + "SELECT c0, c1, CAST(sum(ann) AS BIGINT) AS ann FROM f_mod7 GROUP BY CUBE (c0, c1)"),
    "conv1d_hours__window": (lambda s, d: relational.window_kernel(_sig(s, d), [fixtures.KERNEL_HOURS - t for t in range(fixtures.KERNEL_HOURS)], 0, 30 * 24 + 24), WORKLOADS["conv1d_hours"].sql()),
    "as_of_lag": (_as_of, f"WITH e AS ({_TICKS}) SELECT l.user_id, l.t, l.event_id, (SELECT max(r.t) FROM e r WHERE r.user_id = l.user_id AND r.event_type = 'purchase' AND r.t <= l.t) AS t_before_as_of FROM e l"),
    "range_pairs": (lambda s, d: relational.range_join(_event_ticks(s, d), _event_ticks(s, d), "user_id", "t", 3600).groupBy("user_id").agg(F.count("*").alias("n")), f"WITH e AS ({_TICKS}) SELECT a.user_id, count(*) AS n FROM e a JOIN e b ON a.user_id = b.user_id AND abs(a.t - b.t) <= 3600 GROUP BY 1"),
    "sessions": (lambda s, d: relational.sessions(_event_ticks(s, d), "user_id", "t", 86_400), f"WITH e AS ({_TICKS}), g AS (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t) <= 86400 THEN 0 ELSE 1 END AS b FROM e), k AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS s FROM g) SELECT user_id, min(t) AS \"first\", max(t) AS \"last\", count(*) AS n FROM k GROUP BY user_id, s"),
    "tumbling_windows": (lambda s, d: _windows(s, d, "1 day"), "SELECT CAST(floor(extract(epoch FROM ts) / 86400) * 86400 AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
    "sliding_windows": (lambda s, d: _windows(s, d, "2 days", "1 day"), "SELECT CAST(floor(extract(epoch FROM ts) / 86400) * 86400 - 86400 * k AS BIGINT) AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) AS o(k) GROUP BY 1, 2"),
    "dictionary_ids": (lambda s, d: tables.dictionary(tables.table(s, d, "orders"), "o_orderpriority"), "SELECT o_orderpriority AS value, row_number() OVER (ORDER BY o_orderpriority) - 1 AS id FROM (SELECT DISTINCT o_orderpriority FROM orders) AS t"),
    "matrix_cells": (lambda s, d: relation(s, d, "emb8").df, FIXTURES["emb8"].duck),
}




def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    """Each workload as the planner runs it, and by each of its evaluators."""
    out: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
    for name, w in WORKLOADS.items():
        out[name] = w.run
        for e in w.evaluators:
            out[f"{name}__{e}"] = lambda s, d, w=w, e=e: w.run(s, d, e)
    return out | {n: run for n, (run, _) in SINGLE.items()}


def oracles() -> dict[str, str]:
    out = {}
    for name, w in WORKLOADS.items():
        sql = w.sql(BY_HAND.get(name))
        out[name] = sql
        out |= {f"{name}__{e}": sql for e in w.evaluators}
    return out | {n: sql for n, (_, sql) in SINGLE.items() if sql}

