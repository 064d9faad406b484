"""Experiment inputs derived from the given tables, for Spark and as SQL text side by side."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.keys import (
    BUILD_PICK, BUILD_TERMS, MODULUS, PROBE_PICK, PROBE_TERMS, assign_zipf, md5_bucket, mixed, mixed_sql, single_key, single_sql, zipf_sql,
)
from ..operators.strategies import Sides
from ..sources.catalog import load
from . import placement

#: Rows of the largest scale's tables, to which the printed sizes refer.
FULL_R, FULL_S = 600_000, 150_000


@dataclass(frozen=True)
class Workload:
    """Two inputs r(a, rh, r_qty, src) and s(b, sh, s_pri, src) on n nodes.

    kind 'zipf': ranks 1..n_values at exponent z on both sides; 'single': one hot key with
    shares r_hot and s_hot.  n_r and n_s are sizes at the largest scale.
    """

    kind: str
    n: int
    n_r: int
    n_s: int
    z: float = 1.2
    n_values: int = 1000
    r_hot: float = 0.0
    s_hot: float = 0.0
    p: float = 0.05
    place: str = "even"
    seed: int = 0
    width: int = 300
    node: int = 0
    hot_key: int = 7

    def _bound(self, n: int, full: int) -> int:
        return int(n / full * MODULUS)

    def sides(self, spark: SparkSession, sf_dir: str) -> Sides:
        r = load(spark, sf_dir, "lineitem").withColumns({"rh": mixed(PROBE_TERMS), "pick": mixed(PROBE_PICK)}).where(F.col("pick") < self._bound(self.n_r, FULL_R))
        s = load(spark, sf_dir, "orders").withColumns({"sh": mixed(BUILD_TERMS), "pick": mixed(BUILD_PICK)}).where(F.col("pick") < self._bound(self.n_s, FULL_S))
        if self.kind == "zipf":
            r, s = assign_zipf(r, "rh", self.z, self.n_values, "a"), assign_zipf(s, "sh", self.z, self.n_values, "b")
        else:
            r = r.withColumn("a", single_key(F.col("rh"), self.r_hot, self.hot_key))
            s = s.withColumn("b", single_key(F.col("sh"), self.s_hot, self.hot_key))
        r = r.withColumn("src", self._src("a", F.col("l_orderkey")))
        s = s.withColumn("src", self._src("b", F.col("o_orderkey")))
        r = r.select("a", "rh", F.col("l_linenumber").cast("long").alias("r_qty"), "src")
        s = s.select("b", "sh", (F.col("o_custkey") % 97).alias("s_pri"), "src")
        return Sides(r, s, "a", "b", F.col("rh"), F.col("sh"), "src", "src", home="example")

    def _src(self, name: str, primary: Column) -> Column:
        key, pick = F.col(name), F.col("pick")
        if self.place == "level":
            return placement.level(name, ["pick", "rh" if name == "a" else "sh"], self.n)
        if self.place == "even":
            return placement.even(pick, self.n)
        if self.place == "by_key":
            return placement.by_key(key, self.n)
        if self.place == "hot_node":
            return placement.hot_node(key, pick, self.n, [self.hot_key, 1], self.node, 0.9)
        if self.place == "range_replica":
            return placement.range_replica(primary, self.n, self.width, self.seed)
        raise ValueError(self.place)

    # ---- the same as SQL ----

    def _src_sql(self, key: str, primary: str) -> str:
        n = self.n
        if self.place == "even":
            return f"(pick % {n})"
        if self.place == "by_key":
            return f"(({key} + 1) % {n})"
        if self.place == "hot_node":
            return f"(CASE WHEN {key} IN ({self.hot_key}, 1) AND (pick // {n}) % 100 < 90 THEN {self.node} ELSE pick % {n} END)"
        if self.place == "level":
            return f"(row_number() OVER (PARTITION BY {key} ORDER BY pick, {'rh' if key == 'a' else 'sh'}) % {n})"
        rng = f"({primary} // {self.width})"
        return f"(({rng} * 5 + ((({rng} * 7919 + {self.seed * 104729}) % 1000003) // 7) % 3) % {n})"

    def ctes(self) -> str:
        """SQL: r0/s0 the selected rows, r and s the inputs (a list of CTEs without WITH)."""
        r0 = f"r0 AS (SELECT l_orderkey AS pk, l_linenumber::BIGINT AS r_qty, {mixed_sql(PROBE_TERMS)} AS rh, {mixed_sql(PROBE_PICK)} AS pick FROM lineitem)"
        s0 = f"s0 AS (SELECT o_orderkey AS pk, o_custkey % 97 AS s_pri, {mixed_sql(BUILD_TERMS)} AS sh, {mixed_sql(BUILD_PICK)} AS pick FROM orders)"
        rb, sb = self._bound(self.n_r, FULL_R), self._bound(self.n_s, FULL_S)
        if self.kind == "zipf":
            zt = f"zt AS {zipf_sql(self.z, self.n_values)}"
            r1 = f"r1 AS (SELECT rank AS a, r0.* FROM r0 JOIN zt ON rh >= low AND rh < high WHERE pick < {rb})"
            s1 = f"s1 AS (SELECT rank AS b, s0.* FROM s0 JOIN zt ON sh >= low AND sh < high WHERE pick < {sb})"
            head = [r0, s0, zt, r1, s1]
        else:
            r1 = f"r1 AS (SELECT {single_sql('rh', self.r_hot, self.hot_key)} AS a, * FROM r0 WHERE pick < {rb})"
            s1 = f"s1 AS (SELECT {single_sql('sh', self.s_hot, self.hot_key)} AS b, * FROM s0 WHERE pick < {sb})"
            head = [r0, s0, r1, s1]
        r = f"r AS (SELECT a, rh, r_qty, {self._src_sql('a', 'pk')} AS src FROM r1)"
        s = f"s AS (SELECT b, sh, s_pri, {self._src_sql('b', 'pk')} AS src FROM s1)"
        return ",\n".join([*head, r, s])

    def class_ctes(self) -> str:
        """SQL: cls(key, cls, rc, sc) of the skewed values, on top of r and s."""
        return f"""rc AS (SELECT a AS key, count(*) AS c FROM r WHERE a IS NOT NULL GROUP BY a),
sc AS (SELECT b AS key, count(*) AS c FROM s WHERE b IS NOT NULL GROUP BY b),
hr AS (SELECT key FROM rc WHERE c >= {self.p} * (SELECT sum(c) FROM rc) - 1e-9),
hs AS (SELECT key FROM sc WHERE c >= {self.p} * (SELECT sum(c) FROM sc) - 1e-9),
hk AS (SELECT key FROM hr UNION SELECT key FROM hs),
cls AS (
  SELECT hk.key, coalesce(rc.c, 0) AS rc, coalesce(sc.c, 0) AS sc,
         CASE WHEN hs.key IS NULL THEN 'PROBE_ONLY' WHEN hr.key IS NULL THEN 'BUILD_ONLY'
              WHEN coalesce(rc.c, 0) >= coalesce(sc.c, 0) THEN 'BOTH_PROBE_HEAVY' ELSE 'BOTH_BUILD_HEAVY' END AS cls
  FROM hk LEFT JOIN hr USING (key) LEFT JOIN hs USING (key) LEFT JOIN rc USING (key) LEFT JOIN sc USING (key))"""

    def with_(self, **changes) -> "Workload":
        return replace(self, **changes)


@dataclass(frozen=True)
class Literal(Workload):
    """A workload of literal (key, src) rows of either side; a row's hash is its place in the list."""

    r_rows: tuple = ()
    s_rows: tuple = ()

    def sides(self, spark: SparkSession, sf_dir: str) -> Sides:
        return literal_sides(spark, (list(self.r_rows), list(self.s_rows)))

    def ctes(self) -> str:
        parts = []
        for name, key, h, rows in (("r", "a", "rh", self.r_rows), ("s", "b", "sh", self.s_rows)):
            values = ", ".join(f"({k}::BIGINT, {i}::BIGINT, {n})" for i, (k, n) in enumerate(rows))
            value = "r_qty" if name == "r" else "s_pri"
            parts.append(f"{name} AS (SELECT {key}, {h}, 0 AS {value}, src FROM (VALUES {values}) v({key}, {h}, src))")
        return ",\n".join(parts)


@dataclass(frozen=True)
class Repeated(Literal):
    """An example's rows over and over: every row of the given tables takes key and node of the row that its second hash picks."""

    def sides(self, spark: SparkSession, sf_dir: str) -> Sides:
        def of(rows: tuple, i: int, kind: str) -> Column:
            return F.element_at(F.array(*[F.lit(row[i]).cast(kind) for row in rows]), (F.pmod(F.col("pick"), F.lit(len(rows))) + 1).cast("int"))

        r = load(spark, sf_dir, "lineitem").select(mixed(PROBE_TERMS).alias("rh"), mixed(PROBE_PICK).alias("pick"), F.col("l_linenumber").cast("long").alias("r_qty"))
        s = load(spark, sf_dir, "orders").select(mixed(BUILD_TERMS).alias("sh"), mixed(BUILD_PICK).alias("pick"), (F.col("o_custkey") % 97).alias("s_pri"))
        r = r.select(of(self.r_rows, 0, "long").alias("a"), "rh", "r_qty", of(self.r_rows, 1, "int").alias("src"))
        s = s.select(of(self.s_rows, 0, "long").alias("b"), "sh", "s_pri", of(self.s_rows, 1, "int").alias("src"))
        return Sides(r, s, "a", "b", F.col("rh"), F.col("sh"), "src", "src", home="example")

    def ctes(self) -> str:
        def side(name: str, key: str, h: str, value: str, rows: tuple, pick: str, terms: str, given: str, table: str) -> str:
            keys, nodes = ([row[i] for row in rows] for i in (0, 1))
            place = f"[{pick} % {len(rows)} + 1]"
            return f"{name} AS (SELECT ({keys}::BIGINT[]){place} AS {key}, {terms} AS {h}, {given} AS {value}, ({nodes}){place} AS src FROM {table})"

        return ",\n".join([
            side("r", "a", "rh", "r_qty", self.r_rows, mixed_sql(PROBE_PICK), mixed_sql(PROBE_TERMS), "l_linenumber::BIGINT", "lineitem"),
            side("s", "b", "sh", "s_pri", self.s_rows, mixed_sql(BUILD_PICK), mixed_sql(BUILD_TERMS), "o_custkey % 97", "orders"),
        ])


def repeated(rows: tuple[list, list], n: int, p: float) -> Repeated:
    return Repeated("repeated", n, len(rows[0]), len(rows[1]), p=p, r_rows=tuple(rows[0]), s_rows=tuple(rows[1]))


def literal(rows: tuple[list, list], n: int, p: float) -> Literal:
    return Literal("literal", n, len(rows[0]), len(rows[1]), p=p, r_rows=tuple(rows[0]), s_rows=tuple(rows[1]))


def inputs_zipf(spark: SparkSession, sf_dir: str, n_r: int, n_s: int, z: float, n: int = 3, n_values: int = 1000, **kw) -> Sides:
    return Workload("zipf", n, n_r, n_s, z=z, n_values=n_values, **kw).sides(spark, sf_dir)


def inputs_single(spark: SparkSession, sf_dir: str, n_r: int, n_s: int, r_share: float, s_share: float, n: int = 12, key: int = 7, **kw) -> Sides:
    return Workload("single", n, n_r, n_s, r_hot=r_share, s_hot=s_share, hot_key=key, **kw).sides(spark, sf_dir)


RATIOS = (1, 2, 5, 10, 20, 30)
ZIPF_FACTORS = (0.0, 0.5, 0.8, 1.0, 1.1, 1.2, 1.3, 1.4, 1.5)
NODES = (3, 6, 9, 12)
SHARES = (0.01, 0.02, 0.03, 0.04, 0.049, 0.05, 0.051, 0.06, 0.07, 0.08, 0.09)
THRESHOLDS = (0.005, 0.01, 0.02, 0.05, 0.1, 0.2)


def ratio_sweep(nodes: int = 3) -> list[tuple[float, Workload, int | None]]:
    return [(k, Workload("zipf", nodes, 10_000 * k, 10_000, z=1.2), None) for k in RATIOS]


def zipf_sweep(nodes: int = 3) -> list[tuple[float, Workload, int | None]]:
    return [(z, Workload("zipf", nodes, 293_000, 10_000, z=z), None) for z in ZIPF_FACTORS]


def scaleout() -> list[tuple[float, Workload, int | None]]:
    return [(n, Workload("zipf", n, 391_000, 19_000, z=1.5), None) for n in NODES]


def threshold_sweep(place: str = "range_replica", seed: int = 0) -> list[tuple[float, Workload, int | None]]:
    return [(h, Workload("single", 12, 195_000, 147_000, r_hot=h, s_hot=0.5, p=0.05, place=place, seed=seed), None) for h in SHARES]


def gateway_sweep() -> list[tuple[float, Workload, int | None]]:
    w = Workload("single", 12, 195_000, 98_000, r_hot=6000 / 195_000, s_hot=3000 / 98_000, p=0.02)
    return [(g, w, g) for g in range(12)]


def scenarios() -> list[tuple[str, Workload, int | None]]:
    """Skew on one node; skew that is even already; rows gathered at the node that owns the hot key."""
    w = Workload("single", 3, 195_000, 98_000, r_hot=0.10, s_hot=0.03, p=0.02)
    return [
        ("one_node_skew", w.with_(place="hot_node", node=1), None),
        ("even_skew", w.with_(place="level"), None),
        ("gateway_home", w.with_(r_hot=4500 / 195_000, s_hot=3000 / 98_000, place="range_replica"), (7 + 1) % 3),
    ]


def p_sweep() -> list[tuple[float, Workload, int | None]]:
    return [(p, Workload("zipf", 3, 293_000, 10_000, z=1.2, p=p), None) for p in THRESHOLDS]


def replica_seeds() -> list[tuple[float, Workload, int | None]]:
    return [(seed, Workload("single", 12, 195_000, 147_000, r_hot=0.06, s_hot=0.5, p=0.05, place="range_replica", seed=seed), None) for seed in range(10)]


def intro() -> tuple[list[tuple[int, int]], list[tuple[int, int]]]:
    """(key, src) rows of three nodes: the probe side on nodes 0 and 1, the build side on 1 and 2; hot key 3 with owner 1."""
    r = [(3, 0)] * 4 + [(1, 0), (2, 1)] + [(3, 1)] * 4
    s = [(3, 1), (3, 2), (1, 2), (2, 2), (5, 1)]
    return r, s


def micro(mirrored: bool = False) -> tuple[list[tuple[int, int]], list[tuple[int, int]]]:
    """The worked example of three nodes with owner (key + 1) mod 3."""
    r = [[6, 6, 2, 2, 2, 1], [6, 6, 2, 3, 4, 5], [6, 6, 0, 7, 8, 9]]
    s = [[6, 0, 0, 2], [6, 0, 1, 3], [6, 6, 0, 5]]
    if mirrored:  # key 6 build-heavy
        r, s = [[6, 2, 2, 2, 1, 4], [6, 2, 3, 4, 5, 8], [6, 6, 0, 7, 8, 9]], [[6, 6, 0, 2], [6, 6, 1, 3], [6, 6, 0, 5]]
    return [(k, i) for i, ks in enumerate(r) for k in ks], [(k, i) for i, ks in enumerate(s) for k in ks]


def literal_sides(spark: SparkSession, rows: tuple[list, list]) -> Sides:
    """Sides of literal (key, src) rows."""
    r = spark.createDataFrame([(i, k, n) for i, (k, n) in enumerate(rows[0])], "rh long, a long, src int")
    s = spark.createDataFrame([(i, k, n) for i, (k, n) in enumerate(rows[1])], "sh long, b long, src int")
    return Sides(r, s, "a", "b", F.col("rh"), F.col("sh"), "src", "src", home="example")


def natural(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """Pairs of given tables with natural skew: (a, ...) and (b, ...)."""
    docs = lambda: load(spark, sf_dir, "documents")
    labels = lambda: load(spark, sf_dir, "labels")
    pairs = {
        "lang": lambda: (docs().select(F.col("lang").alias("a"), "doc_id"), docs().select(F.col("lang").alias("b"), F.col("doc_id").alias("other_id"))),
        "quality_toxic": lambda: (labels().select(F.col("quality").cast("long").alias("a"), "doc_id"), labels().select(F.col("toxic").cast("long").alias("b"), F.col("doc_id").alias("other_id"))),
        "linenumber_turn": lambda: (
            load(spark, sf_dir, "lineitem").select(F.col("l_linenumber").cast("long").alias("a"), "l_orderkey"),
            load(spark, sf_dir, "conversations").select(F.col("turn").alias("b"), "conv_id"),
        ),
        "quantity_size": lambda: (
            load(spark, sf_dir, "lineitem").select(F.col("l_quantity").cast("long").alias("a"), "l_orderkey"),
            load(spark, sf_dir, "part").select(F.col("p_size").cast("long").alias("b"), "p_partkey"),
        ),
        "type_priority": lambda: (
            load(spark, sf_dir, "events").select(md5_bucket(F.col("event_type"), 7).alias("a"), "event_id"),
            load(spark, sf_dir, "orders").select(md5_bucket(F.col("o_orderpriority"), 7).alias("b"), "o_orderkey"),
        ),
        "orderkey": lambda: (
            load(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("a"), "l_linenumber"),
            load(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("b"), "o_custkey"),
        ),
    }
    return pairs[name]()
