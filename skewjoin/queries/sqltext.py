"""SQL text of routing and cost: its own policy matrix and arithmetic, against which the engine's are checked."""

from __future__ import annotations

from ..plans.classify import BOTH_BUILD, BOTH_PROBE, BUILD_ONLY, PROBE_ONLY
from ..plans.workloads import Workload

_CLASSES = (PROBE_ONLY, BUILD_ONLY, BOTH_PROBE, BOTH_BUILD)
HASH, STAY, SCATTER, REPLICATE, GRID = "HASH", "STAY", "SCATTER", "REPLICATE", "GRID"
#: What the probe and the build side of each class do: probe-only, build-only, two-sided probe-heavy, two-sided build-heavy.
_MATRIX = {
    "hash_all": ("HASH HASH", "HASH HASH", "HASH HASH", "HASH HASH"),
    "stay_replicate": ("STAY REPLICATE", "REPLICATE STAY", "STAY REPLICATE", "REPLICATE STAY"),
    "stay_replicate_grid": ("STAY REPLICATE", "REPLICATE STAY", "GRID GRID", "GRID GRID"),
    "scatter_replicate": ("SCATTER REPLICATE", "REPLICATE SCATTER", "SCATTER REPLICATE", "REPLICATE SCATTER"),
    "flow": ("STAY REPLICATE", "REPLICATE STAY", "GRID GRID", "GRID GRID"),
    "grid": ("GRID GRID", "GRID GRID", "GRID GRID", "GRID GRID"),
    "four_route": ("STAY REPLICATE", "HASH HASH", "SCATTER REPLICATE", "REPLICATE SCATTER"),
    "four_route_scatter": ("SCATTER REPLICATE", "HASH HASH", "SCATTER REPLICATE", "REPLICATE SCATTER"),
    "subset_replicate": ("STAY REPLICATE", "HASH HASH", "STAY REPLICATE", "STAY REPLICATE"),
}
_ACTIONS = {name: {c: tuple(pair.split()) for c, pair in zip(_CLASSES, row)} for name, row in _MATRIX.items()}


def _case(column: str, values: dict[str, str], other: str) -> str:
    return f"CASE {column} " + " ".join(f"WHEN '{k}' THEN {v}" for k, v in values.items()) + f" ELSE {other} END"


def _shape(n: int) -> str:
    """SQL: shp(key, ga, gc), the grid of each skewed value."""
    root = int(n**0.5)
    divisors = ", ".join(str(d) for d in range(1, n + 1) if n % d == 0)
    return f"""shp AS (
  SELECT key, ga, {n} // ga AS gc FROM (
    SELECT key, arg_min(d, (greatest(rc, 1) * ({n} // d) + greatest(sc, 1) * d) * 1000 + abs(d - {root})) AS ga
    FROM cls, (SELECT unnest([{divisors}]) AS d) GROUP BY key))"""


def routed(w: Workload, policy: str) -> str:
    """SQL CTEs rd(a, src, dst, ...) and sd(b, src, dst, ...) on top of the classes."""
    actions = _ACTIONS[policy]
    probe = _case("cls", {c: f"'{actions[c][0]}'" for c in _CLASSES}, "'HASH'")
    build = _case("cls", {c: f"'{actions[c][1]}'" for c in _CLASSES}, "'HASH'")
    n = w.n
    return f"""{w.ctes()},
{w.class_ctes()},
{_shape(n)},
act AS (SELECT key, {probe} AS pa, {build} AS ba, ga, gc FROM cls JOIN shp USING (key)),
rd AS (
  SELECT a, rh, r_qty, src, unnest(CASE pa WHEN '{STAY}' THEN [src::BIGINT] WHEN '{SCATTER}' THEN [rh % {n}] WHEN '{REPLICATE}' THEN range(0, {n})
    WHEN '{GRID}' THEN list_transform(range(0, gc), lambda i: (rh % ga) * gc + i) ELSE [(a + 1) % {n}] END) AS dst
  FROM r LEFT JOIN act ON a = key),
sd AS (
  SELECT b, sh, s_pri, src, unnest(CASE ba WHEN '{STAY}' THEN [src::BIGINT] WHEN '{SCATTER}' THEN [sh % {n}] WHEN '{REPLICATE}' THEN range(0, {n})
    WHEN '{GRID}' THEN list_transform(range(0, ga), lambda i: (sh % gc) + i * gc) ELSE [(b + 1) % {n}] END) AS dst
  FROM s LEFT JOIN act ON b = key)"""


def _charged(policy: str, form: str) -> dict[str, list[str]]:
    """Per class the actions charged, named from the side that stays or scatters."""
    names = {(HASH, HASH): "HASH", (STAY, REPLICATE): "STAY_R", (REPLICATE, STAY): "STAY_S", (SCATTER, REPLICATE): "SCAT_R", (REPLICATE, SCATTER): "SCAT_S", (GRID, GRID): "GRID"}
    out = {c: [names[_ACTIONS[policy][c]]] for c in _CLASSES}
    if form == "printed":
        if policy.startswith("four_route"):
            out[BUILD_ONLY] = []
        if policy == "stay_replicate":
            out[BOTH_PROBE] = out[BOTH_BUILD] = ["STAY_R", "STAY_S"]
    return out


def costs(w: Workload, policies, gateway: int | None, form: str = "complete", config: str = "0") -> str:
    """A SQL query (config, strategy, moved, busiest, merged, total, chosen) for one workload."""
    n = w.n
    parts = []
    for place, policy in enumerate(policies):
        charged = _charged(policy, form)
        lists = _case("cls", {c: "[" + ", ".join(f"'{a}'" for a in v) + "]::VARCHAR[]" for c, v in charged.items()}, "[]::VARCHAR[]")
        parts.append(f"SELECT {place} AS place, '{policy}' AS strategy, key, unnest({lists}) AS act FROM cls")
    outside = "0" if gateway is None else f"sum(CASE WHEN i <> {gateway} THEN rr * ss ELSE 0 END)"
    return f"""SELECT {config} AS config, strategy, round(moved, 3) AS moved, round(busiest, 3) AS busiest, round(merged, 3) AS merged, round(moved + busiest + merged, 3) AS total,
       row_number() OVER (ORDER BY moved + busiest + merged, place) = 1 AS chosen
FROM (
WITH {w.ctes()},
{w.class_ctes()},
{_shape(n)},
nodes AS (SELECT unnest(range(0, {n})) AS i),
rn AS (SELECT a AS key, src AS i, count(*) AS c FROM r GROUP BY 1, 2),
sn AS (SELECT b AS key, src AS i, count(*) AS c FROM s GROUP BY 1, 2),
prof AS (
  SELECT cls.key, nodes.i, rc, sc, (cls.key + 1) % {n} AS own, coalesce(rn.c, 0) AS ri, coalesce(sn.c, 0) AS si, ga, gc
  FROM cls CROSS JOIN nodes JOIN shp ON shp.key = cls.key LEFT JOIN rn ON rn.key = cls.key AND rn.i = nodes.i LEFT JOIN sn ON sn.key = cls.key AND sn.i = nodes.i),
ch AS ({' UNION ALL '.join(parts)}),
x AS (
  SELECT place, strategy, act, prof.*,
    CASE act WHEN 'HASH' THEN CASE WHEN i = own THEN rc ELSE 0 END WHEN 'STAY_R' THEN ri WHEN 'SCAT_R' THEN rc / {n}.0 WHEN 'GRID' THEN rc::DOUBLE / ga ELSE rc END::DOUBLE AS rr,
    CASE act WHEN 'HASH' THEN CASE WHEN i = own THEN sc ELSE 0 END WHEN 'STAY_S' THEN si WHEN 'SCAT_S' THEN sc / {n}.0 WHEN 'GRID' THEN sc::DOUBLE / gc ELSE sc END::DOUBLE AS ss,
    CASE act WHEN 'HASH' THEN (rc + sc) * {n - 1} / {n}.0 WHEN 'STAY_R' THEN sc * {n - 1} WHEN 'STAY_S' THEN rc * {n - 1}
      WHEN 'SCAT_R' THEN rc * {n - 1} / {n}.0 + sc * {n - 1} WHEN 'SCAT_S' THEN sc * {n - 1} / {n}.0 + rc * {n - 1}
      ELSE (rc * gc + sc * ga) * {n - 1} / {n}.0 END::DOUBLE AS net
  FROM ch JOIN prof USING (key)),
per AS (SELECT place, strategy, i, sum(rr + ss + rr * ss) AS work FROM x GROUP BY ALL),
top AS (SELECT place, strategy, max(work) AS busiest FROM per GROUP BY ALL),
mv AS (SELECT place, strategy, sum(net) / {n} AS moved, {outside} AS merged FROM x GROUP BY ALL),
names AS (SELECT * FROM (VALUES {', '.join(f"({i}, '{p}')" for i, p in enumerate(policies))}) v(place, strategy))
SELECT place, strategy, coalesce(moved, 0)::DOUBLE AS moved, coalesce(busiest, 0)::DOUBLE AS busiest, coalesce(merged, 0)::DOUBLE AS merged
FROM names LEFT JOIN mv USING (place, strategy) LEFT JOIN top USING (place, strategy)) q"""


def sweep(configs, policies, form: str = "complete") -> str:
    """The costs of several configurations, one below the other."""
    return "\nUNION ALL\n".join(f"({costs(w, policies, g, form, _literal(c))})" for c, w, g in configs)


def loads(configs, policies) -> str:
    """Observed work of the busiest node for several configurations and strategies."""
    return "\nUNION ALL\n".join(
        f"""(SELECT {_literal(c)} AS config, '{p}' AS strategy, max(w)::BIGINT AS busiest_work, sum(w)::BIGINT AS all_work, round(max(w) * {w.n} / sum(w), 6) AS max_over_mean FROM (
WITH {routed(w, p)},
rk AS (SELECT dst, a AS key, count(*) AS r FROM rd GROUP BY 1, 2), sk AS (SELECT dst, b AS key, count(*) AS s FROM sd GROUP BY 1, 2)
SELECT dst, sum(coalesce(r, 0) + coalesce(s, 0) + coalesce(r, 0) * coalesce(s, 0)) AS w FROM rk FULL JOIN sk USING (dst, key) GROUP BY dst) t)"""
        for c, w, _ in configs for p in policies
    )


def _literal(config) -> str:
    return f"'{config}'"
