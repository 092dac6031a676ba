"""Registered queries of the engine and DuckDB SQL for their answers.

The SQL counts with ends fixed on one side, the engine mostly with priority pivots, so
the two check each other.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import experiments, graphs, ingest, plans, streaming
from .functions import GOLDEN, PRIME, choose2, owner, total
from .model import SignedGraph
from .operators import assign, count, index, measures, metrics, relational, tiles
from .schemas import TOTAL
from .sources import ingest_audit, table

Query = Callable[[SparkSession, str], DataFrame]
ALL = ("g1", "g2", "g3", "g4", "g5", "g6", "g7")

_RAW = {
    "g1": "SELECT l_partkey AS u, l_suppkey AS v, CASE WHEN l_returnflag <> 'R' THEN 1 ELSE 0 END AS sign, l_shipdate AS ts, l_orderkey AS k1, l_linenumber AS k2 FROM lineitem",
    "g2": "SELECT o_custkey AS u, l_suppkey AS v, CASE WHEN l_returnflag <> 'R' THEN 1 ELSE 0 END AS sign, l_shipdate AS ts, l_orderkey AS k1, l_linenumber AS k2 FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "g3": "SELECT o_custkey AS u, l_partkey AS v, CASE WHEN l_quantity >= 25 THEN 1 ELSE 0 END AS sign, l_shipdate AS ts, l_orderkey AS k1, l_linenumber AS k2 FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "g4": "SELECT o_custkey AS u, CAST(regexp_extract(p_brand, '([0-9]+)', 1) AS BIGINT) AS v, CASE WHEN l_quantity >= 25 THEN 1 ELSE 0 END AS sign, l_shipdate AS ts, l_orderkey AS k1, l_linenumber AS k2 FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey",
    "g5": "SELECT user_id AS u, CAST(CASE event_type WHEN 'click' THEN 1 WHEN 'error' THEN 2 WHEN 'purchase' THEN 3 WHEN 'signup' THEN 4 WHEN 'view' THEN 5 END AS BIGINT) AS v, CASE WHEN value >= 10 THEN 1 ELSE 0 END AS sign, ts, event_id AS k1, 0 AS k2 FROM events",
    "g6": "SELECT user_id AS u, CAST(json_extract_string(props, '$.k') AS BIGINT) AS v, CASE WHEN event_type <> 'error' THEN 1 ELSE 0 END AS sign, ts, event_id AS k1, 0 AS k2 FROM events",
}


def _ctes(g: str) -> str:
    """``raw`` (interactions) and ``e`` (edges) of a graph."""
    if g.startswith("w"):  # given inline by the caller
        return "given AS (SELECT 1)"
    if g == "g7":
        return "e AS (SELECT vec_id AS u, i - 1 AS v, CASE WHEN embedding[i] >= 0 THEN 1 ELSE 0 END AS sign FROM embeddings, range(1, 65) t(i))"
    if g == "g8":
        return "e AS (SELECT d.doc_id AS u, w AS v, max(CASE WHEN quality = 1 THEN 1 ELSE 0 END) AS sign FROM documents d JOIN labels l ON d.doc_id = l.doc_id, unnest(list_distinct(regexp_extract_all(lower(text), '[a-zà-ÿ]+'))) t(w) GROUP BY d.doc_id, w)"
    return f"raw AS ({_RAW[g]}), e AS (SELECT u, v, arg_max(sign, (ts, k1, k2, sign)) AS sign FROM raw WHERE u IS NOT NULL AND v IS NOT NULL GROUP BY u, v)"


_PRIO = """t AS (SELECT u * 2 AS gu, v * 2 + 1 AS gv, sign FROM e), d AS (SELECT g AS gid, count(*) AS deg FROM (SELECT gu AS g FROM t UNION ALL SELECT gv FROM t) GROUP BY g),
x AS (SELECT gu, gv, sign, a.deg AS du, b.deg AS dv FROM t JOIN d a ON gu = a.gid JOIN d b ON gv = b.gid),
o AS (SELECT CASE WHEN up THEN gu ELSE gv END AS hi, CASE WHEN up THEN du ELSE dv END AS hi_deg, CASE WHEN up THEN gv ELSE gu END AS lo, CASE WHEN up THEN dv ELSE du END AS lo_deg, sign FROM (SELECT *, du > dv OR (du = dv AND gu > gv) AS up FROM x)),
n AS (SELECT lo AS mid, hi AS g, hi_deg AS gd, sign, true AS above FROM o UNION ALL SELECT hi, lo, lo_deg, sign, false FROM o)"""


def _pairs(side: str) -> str:
    end, mid = ("u", "v") if side == "U" else ("v", "u")
    return f"""p AS (SELECT a.{end} AS a, b.{end} AS b, sum(CASE WHEN a.sign = 1 AND b.sign = 1 THEN 1 ELSE 0 END) AS pp, sum(CASE WHEN a.sign = 0 AND b.sign = 0 THEN 1 ELSE 0 END) AS nn,
sum(CASE WHEN a.sign = 1 AND b.sign = 0 THEN 1 ELSE 0 END) AS pn, sum(CASE WHEN a.sign = 0 AND b.sign = 1 THEN 1 ELSE 0 END) AS np FROM e a JOIN e b ON a.{mid} = b.{mid} AND a.{end} < b.{end} GROUP BY 1, 2),
q AS (SELECT a, b, pp + nn AS b1, pn + np AS b2, pp, nn, pn, np FROM p)"""


def _sum(x: str, name: str) -> str:
    return f"CAST(coalesce(sum({x}), 0) AS BIGINT) AS {name}"


_BAL = "b1 * (b1 - 1) // 2 + b2 * (b2 - 1) // 2"


def _bbf(g: str) -> str:
    return f"WITH {_ctes(g)}, {_pairs('U' if g == 'g8' else 'V')} SELECT {_sum(_BAL, 'balanced')} FROM q"


def _narrow(rows: DataFrame) -> DataFrame:
    """Decimal totals as longs, for comparison: these tables' totals fit."""
    return rows.select(*[F.col(c).cast("long").alias(c) if t == TOTAL else F.col(c) for c, t in rows.dtypes])


#: No pivot is split: per-bin rows are those of the assignment alone.
WHOLE = experiments.WHOLE


def _owner(x: str, parts: int) -> str:
    return f"CAST((({x}) % {PRIME} * {GOLDEN} % {PRIME}) * {parts} // {PRIME} AS INT)"


def _greedy(source: str, bins: int, out: str) -> str:
    """Tables that pack (unit, load) of ``source`` as the greedy assigner does: ``out`` has unit and bin."""
    best = "list_position(r.sums, list_min(r.sums))"
    return f"""{out}_s AS (SELECT *, row_number() OVER (ORDER BY load DESC, unit) AS i FROM {source}),
{out}_r AS (SELECT CAST(0 AS BIGINT) AS i, CAST(0 AS BIGINT) AS unit, 0 AS bin, CAST(list_transform(range({bins}), lambda x: 0) AS BIGINT[]) AS sums UNION ALL
SELECT s.i, s.unit, CAST({best} - 1 AS INT), list_transform(r.sums, lambda x, j: CASE WHEN j = {best} THEN x + s.load ELSE x END) FROM {out}_r r JOIN {out}_s s ON s.i = r.i + 1),
{out} AS (SELECT unit, bin FROM {out}_r WHERE i > 0)"""


def _melt(experiment: str, graph: str, config: str, sql: str, metrics_: tuple[str, ...]) -> str:
    """Rows of an experiment from the columns of one row."""
    return "SELECT '{}' AS experiment, '{}' AS graph, '{}' AS config, unnest([{}]) AS metric, unnest([{}]) AS value FROM ({})".format(experiment, graph, config, ", ".join(f"'{m}'" for m in metrics_), ", ".join(f'CAST("{m}" AS DOUBLE)' for m in metrics_), sql)


class _Registry:
    def __init__(self) -> None:
        self.queries: dict[str, Query] = {}
        self.sql: dict[str, str] = {}

    def add(self, name: str, query: Query, sql: str | None = None) -> None:
        self.queries[name] = lambda spark, sf: _narrow(query(spark, sf))
        if sql:
            self.sql[name] = re.sub(r"\bpivot\b", '"pivot"', sql)  # a keyword in DuckDB


def _on(g: str, f: Callable[[SignedGraph], DataFrame]) -> Query:
    return lambda spark, sf: f(graphs.build(spark, sf, g))


def _edges(r: _Registry) -> None:
    for g in ALL:
        r.add(f"edges_{g}", _on(g, lambda x: x.edges.select("u", "v", F.col("sign").cast("int").alias("sign"))), f"WITH {_ctes(g)} SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v, CAST(sign AS INT) AS sign FROM e")
        r.add(f"unsigned_{g}", _on(g, ingest.as_unsigned), f"WITH {_ctes(g)} SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v FROM e")
        wedge = lambda mid, name: f"(SELECT {_sum('d * (d - 1) // 2', name)} FROM (SELECT count(*) AS d FROM e GROUP BY {mid}))"
        r.add(
            f"profile_{g}",
            _on(g, measures.graph_profile),
            f"WITH {_ctes(g)}, {_pairs('V')} SELECT count(DISTINCT u) AS n_u, count(DISTINCT v) AS n_v, count(*) AS n_e, round(count(*) / (count(DISTINCT u) * count(DISTINCT v)), 6) AS density, CAST(sum(1 - sign) AS BIGINT) AS negatives, (SELECT max(c) FROM (SELECT count(*) AS c FROM e GROUP BY u)) AS max_deg_u, (SELECT max(c) FROM (SELECT count(*) AS c FROM e GROUP BY v)) AS max_deg_v, {wedge('v', 'x')} AS wedges_u_ends, {wedge('u', 'x')} AS wedges_v_ends, (SELECT {_sum(_BAL, 'b')} FROM q) AS balanced FROM e",
        )
    for g in ALL[:-1]:
        r.add(
            f"duplicates_{g}",
            lambda s, d, g=g: ingest.duplicate_profile(graphs.interactions(s, d, g)),
            f"WITH {_ctes(g)}, k AS (SELECT u, v, count(*) AS n, min(sign) AS a, max(sign) AS b, max(CASE WHEN sign = 1 THEN ts END) AS p, max(CASE WHEN sign = 0 THEN ts END) AS q FROM raw GROUP BY u, v) SELECT CAST(sum(n) AS BIGINT) AS interactions, count(*) AS pairs, count(*) FILTER (n > 1) AS repeated, count(*) FILTER (a <> b) AS conflicting, count(*) FILTER (a <> b AND p = q) AS tied FROM k",
        )
    for policy, sql in {
        "earliest": "arg_min(sign, (ts, k1, k2, sign))",
        "majority": "CASE WHEN 2 * sum(sign) >= count(*) THEN 1 ELSE 0 END",
        "sum": "CASE WHEN 2 * sum(sign) > count(*) THEN 1 ELSE 0 END",
        "drop_conflicts": "max(sign)",
    }.items():
        having = {"sum": " HAVING 2 * sum(sign) <> count(*)", "drop_conflicts": " HAVING min(sign) = max(sign)"}.get(policy, "")
        r.add(f"policy_{policy}_g1", lambda s, d, p=policy: ingest.resolve_conflicts(graphs.interactions(s, d, "g1"), p).select("u", "v", F.col("sign").cast("int").alias("sign")), f"WITH {_ctes('g1')} SELECT u, v, CAST({sql} AS INT) AS sign FROM raw GROUP BY u, v{having}")
    r.add("sign_flips_g4", lambda s, d: ingest.sign_flips(graphs.interactions(s, d, "g4")), f"WITH {_ctes('g4')} SELECT u, v, CAST(sum(CASE WHEN was <> sign THEN 1 ELSE 0 END) AS BIGINT) AS flips FROM (SELECT *, lag(sign) OVER (PARTITION BY u, v ORDER BY ts, k1, k2, sign) AS was FROM raw) GROUP BY u, v")
    r.add("rating_mean_g3", lambda s, d: _rated(s, d, "mean"), _rated_sql("(SELECT avg(l_quantity) FROM lineitem)"))
    r.add("rating_user_mean_g3", lambda s, d: _rated(s, d, "user_mean"), _rated_sql("avg(l_quantity) OVER (PARTITION BY o_custkey)"))
    for g in ("g1", "g3"):
        parts = " UNION ALL ".join(f"SELECT {n} AS neg_pct, {_sum(_BAL, 'balanced')}, {_sum('(b1 + b2) * (b1 + b2 - 1) // 2', 'total')} FROM q{n}" for n in (10, 30, 50, 70, 90))
        tables = ", ".join(f"p{n} AS (SELECT a.v AS a, b.v AS b, sum(CASE WHEN (a.h >= {n}) = (b.h >= {n}) THEN 1 ELSE 0 END) AS b1, sum(CASE WHEN (a.h >= {n}) <> (b.h >= {n}) THEN 1 ELSE 0 END) AS b2 FROM h a JOIN h b ON a.u = b.u AND a.v < b.v GROUP BY 1, 2), q{n} AS (SELECT * FROM p{n})" for n in (10, 30, 50, 70, 90))
        r.add(f"sign_sweep_{g}", _on(g, _sweep), f"WITH {_ctes(g)}, h AS (SELECT u, v, CAST('0x' || substr(md5(u || '|' || v || '|42'), 1, 8) AS BIGINT) % 100 AS h FROM e), {tables} {parts}")


def _rated(spark: SparkSession, sf: str, threshold: str) -> DataFrame:
    orders = table(spark, sf, "orders").select("o_orderkey", F.col("o_custkey").alias("u"))
    rows = table(spark, sf, "lineitem").join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return ingest.sign_from_rating(rows, "l_quantity", threshold).groupBy("u").agg(F.sum(F.col("sign").cast("long")).alias("positive"), F.count(F.lit(1)).alias("n"))


def _rated_sql(cut: str) -> str:
    return f"SELECT u, CAST(sum(CASE WHEN q >= c THEN 1 ELSE 0 END) AS BIGINT) AS positive, count(*) AS n FROM (SELECT o_custkey AS u, l_quantity AS q, {cut} AS c FROM lineitem JOIN orders ON l_orderkey = o_orderkey) GROUP BY u"


def _sweep(graph: SignedGraph) -> DataFrame:
    pcts = (10, 30, 50, 70, 90)
    if len(pcts) * tiles.wedges_of(graph, "V") > tiles.FAR:  # one topology: its wedges are formed once
        masks = sum((F.shiftleft((ingest.random_bucket(42) >= p).cast("int"), k) for k, p in enumerate(pcts)), F.lit(0))
        rows = tiles.class_counts(graph.cached(), "V", masks, len(pcts))
        both = F.col("symmetric") + F.col("asymmetric")
        every = count.pairs(graph, "V").agg(total(choose2(F.col("b1") + F.col("b2"))).cast("long").alias("total"))
        return rows.crossJoin(every).select(F.get(F.array(*map(F.lit, pcts)), F.col("layer")).alias("neg_pct"), both.cast("long").alias("balanced"), "total")
    out = None
    for pct, signed in ingest.sign_sweep(graph).items():
        row = count.pairs(signed, "V").agg(total(choose2(F.col("b1")) + choose2(F.col("b2"))).cast("long").alias("balanced"), total(choose2(F.col("b1") + F.col("b2"))).cast("long").alias("total")).select(F.lit(pct).alias("neg_pct"), "balanced", "total")
        out = row if out is None else out.unionByName(row)
    return out


def _index(r: _Registry) -> None:
    for g in ("g1", "g3", "g5", "g6"):
        base = f"WITH {_ctes(g)}, {_PRIO}"
        r.add(f"degree_{g}", _on(g, index.degrees), f"{base} SELECT gid, deg FROM d")
        r.add(f"priority_{g}", _on(g, lambda x: index.compact_ids(index.degrees(x)).select("gid", "rank_id")), f"{base} SELECT gid, row_number() OVER (ORDER BY deg, gid) - 1 AS rank_id FROM d")
        r.add(f"owner_{g}", _on(g, lambda x: index.degrees(x).select("gid", owner(F.col("gid"), 16).alias("owner"))), f"{base} SELECT gid, {_owner('gid', 16)} AS owner FROM d")
        r.add(f"compact_hash_{g}", _on(g, lambda x: index.compact_ids(index.degrees(x), "hash", 16).select("gid", "rank_id")), f"{base} SELECT gid, row_number() OVER (ORDER BY {_owner('gid', 16)}, gid) - 1 AS rank_id FROM d")
        r.add(f"oriented_{g}", _on(g, lambda x: index.orient(x).select("hi", "lo", F.col("sign").cast("int").alias("sign"))), f"{base} SELECT hi, lo, CAST(sign AS INT) AS sign FROM o")
        r.add(f"workload_full_{g}", _on(g, index.workload), f"{base} SELECT pivot, CAST(sum(l) AS BIGINT) AS load FROM (SELECT gu AS pivot, dv AS l FROM x UNION ALL SELECT gv, du FROM x) GROUP BY pivot")
        r.add(f"workload_restricted_{g}", _on(g, lambda x: index.workload(x, "restricted")), f"{base} SELECT gid AS pivot, CAST(coalesce(sum(lo_deg), 0) AS BIGINT) AS load FROM d LEFT JOIN o ON hi = gid GROUP BY gid")
        exact = "w AS (SELECT g, above, row_number() OVER (PARTITION BY mid ORDER BY gd, g) - 1 AS below FROM n)"
        r.add(f"workload_exact_{g}", _on(g, lambda x: index.workload(x, "exact")), f"{base}, {exact} SELECT gid AS pivot, CAST(coalesce(sum(below), 0) AS BIGINT) AS load FROM d LEFT JOIN w ON g = gid AND above GROUP BY gid")
        r.add(f"work_bounds_{g}", _on(g, index.work_bounds), f"{base}, {exact} SELECT count(*) AS edges, CAST(sum(lo_deg) AS BIGINT) AS sum_min, CAST(sum(hi_deg + lo_deg) AS BIGINT) AS sum_full, (SELECT CAST(sum(below) AS BIGINT) FROM w WHERE above) AS wedges FROM o")


def _counts(r: _Registry) -> None:
    for g in ALL:
        r.add(f"bbf_pivot_local_{g}", _on(g, lambda x: count.count_pivot_local(x, workload="restricted")), _bbf(g))
        r.add(f"bbf_wedge_agg_V_{g}", _on(g, lambda x: count.count_wedge_agg(x, "V")), _bbf(g))
        r.add(f"bbf_wedge_agg_priority_{g}", _on(g, count.count_wedge_agg), _bbf(g))
        r.add(f"bbf_auto_{g}", _on(g, plans.count_auto), _bbf(g))
        summary = f"WITH {_ctes(g)}, {_pairs('V')}, s AS (SELECT {_sum('(b1 + b2) * (b1 + b2 - 1) // 2', 'total')}, {_sum(_BAL, 'balanced')}, {_sum('b1 * b2', 'unbalanced')} FROM q) SELECT total, balanced, unbalanced, round(balanced / nullif(total, 0), 6) AS ratio FROM s"
        r.add(f"balance_summary_{g}", _on(g, measures.balance_summary), summary)
        shapes = ", ".join([_sum("pp * (pp - 1) // 2", '"none"'), _sum("nn * (nn - 1) // 2", "four"), _sum("pn * (pn - 1) // 2 + np * (np - 1) // 2", "two_on_v"), _sum("pp * nn", "two_on_u"), _sum("pn * np", "two_diagonal"), _sum("pp * (pn + np)", '"one"'), _sum("nn * (pn + np)", "three")])
        r.add(f"census_{g}", _on(g, lambda x: measures.pattern_census(x, "V")), f"WITH {_ctes(g)}, {_pairs('V')} SELECT {shapes} FROM q")
        paths = f"WITH {_ctes(g)}, {_PRIO}, {_pairs('V')}, s AS (SELECT {_sum('(b1 + b2) * (b1 + b2 - 1) // 2', 'total')}, {_sum(_BAL, 'balanced')} FROM q), k AS (SELECT CAST(sum((du - 1) * (dv - 1)) AS BIGINT) AS paths FROM x) SELECT paths, total, balanced, round(4 * total / nullif(paths, 0), 6) AS coefficient, round(4 * balanced / nullif(paths, 0), 6) AS balanced_coefficient FROM s, k"
        r.add(f"clustering_{g}", _on(g, measures.clustering), paths)
    r.add("bbf_wedge_agg_U_g8", _on("g8", lambda x: count.count_wedge_agg(x, "U")), _bbf("g8"))
    for g in ("g1", "g3", "g5", "g6"):
        r.add(f"bbf_wedge_agg_U_{g}", _on(g, lambda x: count.count_wedge_agg(x, "U")), _bbf(g))
        r.add(f"bbf_pivot_arrow_{g}", _on(g, lambda x: count.count_pivot_local(x, form="arrow")), _bbf(g))
        r.add(f"bbf_flat_{g}", _on(g, lambda x: count.count_pivot_local(x, bins=12, threads=1)), _bbf(g))
        r.add(f"bbf_hybrid_{g}", _on(g, lambda x: count.count_pivot_local(x, bins=4, threads=3, assigner="lpt_scalable")), _bbf(g))
        r.add(f"bbf_blocks_{g}", _on(g, lambda x: count.count_pivot_local(x, assigner="blocks")), _bbf(g))
        r.add(f"bbf_snake_{g}", _on(g, lambda x: count.count_pivot_local(x, assigner="snake", workload="exact")), _bbf(g))
        r.add(f"bbf_lpt_{g}", _on(g, lambda x: count.count_pivot_local(x, bins=4, threads=3, assigner="lpt", form="arrow")), _bbf(g))
        r.add(f"bbf_split_hot_{g}", _on(g, lambda x: count.count_pivot_local(x, assigner="hash", workload="restricted", max_load=5_000)), _bbf(g))
        r.add(f"bbf_shared_{g}", _on(g, count.count_shared), _bbf(g))
        r.add(f"bbf_serial_{g}", _on(g, count.count_serial), _bbf(g))
        r.add(f"bbf_core_{g}", _on(g, lambda x: count.count_wedge_agg(index.prune_core(x), "V")), _bbf(g))
        for side in ("U", "V"):
            r.add(f"class_split_{side}_{g}", _on(g, lambda x, s=side: measures.class_split(x, s)), f"WITH {_ctes(g)}, {_pairs(side)} SELECT {_sum('b1 * (b1 - 1) // 2', 'symmetric')}, {_sum('b2 * (b2 - 1) // 2', 'asymmetric')} FROM q")
            k = side.lower()
            r.add(f"vertex_counts_{side}_{g}", _on(g, lambda x, s=side: measures.vertex_counts(x, s)), f"WITH {_ctes(g)}, {_pairs(side)}, h AS (SELECT a AS k, {_BAL} AS n FROM q UNION ALL SELECT b, {_BAL} FROM q) SELECT e.{k} AS key, CAST(coalesce(max(s), 0) AS BIGINT) AS balanced FROM (SELECT DISTINCT {k} FROM e) e LEFT JOIN (SELECT k, sum(n) AS s FROM h GROUP BY k) h ON h.k = e.{k} GROUP BY e.{k}")
            r.add(f"top_pairs_{side}_{g}", _on(g, lambda x, s=side: measures.top_pairs(x, 10, s)), f"WITH {_ctes(g)}, {_pairs(side)} SELECT CAST(a AS BIGINT) AS a, CAST(b AS BIGINT) AS b, CAST({_BAL} AS BIGINT) AS balanced FROM q ORDER BY balanced DESC, a, b LIMIT 10")
        r.add(f"edge_counts_{g}", _on(g, lambda x: measures.edge_counts(x, "V")), f"WITH {_ctes(g)}, {_pairs('V')}, w AS (SELECT x.u, x.v AS a, y.v AS b, x.sign = y.sign AS same FROM e x JOIN e y ON x.u = y.u AND x.v < y.v), c AS (SELECT w.u, w.a, w.b, CASE WHEN same THEN b1 ELSE b2 END - 1 AS n FROM w JOIN q ON w.a = q.a AND w.b = q.b), h AS (SELECT u, a AS v, n FROM c UNION ALL SELECT u, b, n FROM c) SELECT e.u, e.v, CAST(coalesce(s, 0) AS BIGINT) AS balanced FROM e LEFT JOIN (SELECT u, v, sum(n) AS s FROM h GROUP BY u, v) h ON e.u = h.u AND e.v = h.v")
    for g in ("g3", "g5", "g6"):
        r.add(f"bbf_signblind_{g}", _on(g, count.count_signblind), f"WITH {_ctes(g)}, {_pairs('V')} SELECT {_sum('(b1 + b2) * (b1 + b2 - 1) // 2', 'total')}, {_sum(_BAL, 'balanced')}, {_sum('b1 * b2', 'wasted')} FROM q")
        r.add(f"bbf_nosep_{g}", _on(g, count.count_no_separation), _bbf(g))
    quad = "SELECT count(*) AS total, CAST(coalesce(sum(CASE WHEN (a.sign + b.sign + c.sign + d.sign) % 2 = 0 THEN 1 ELSE 0 END), 0) AS BIGINT) AS balanced FROM e a JOIN e b ON a.u = b.u AND a.v < b.v JOIN e c ON a.v = c.v AND a.u < c.u JOIN e d ON d.u = c.u AND d.v = b.v"
    r.add("bbf_bruteforce_g5", _on("g5", count.count_bruteforce), f"WITH {_ctes('g5')} {quad}")
    r.add("enumerate_g5", _on("g5", count.enumerate_butterflies), f"WITH {_ctes('g5')} SELECT a.u AS u1, c.u AS u2, a.v AS v1, b.v AS v2, CAST(4 - (a.sign + b.sign + c.sign + d.sign) AS INT) AS negatives FROM e a JOIN e b ON a.u = b.u AND a.v < b.v JOIN e c ON a.v = c.v AND a.u < c.u JOIN e d ON d.u = c.u AND d.v = b.v WHERE (a.sign + b.sign + c.sign + d.sign) % 2 = 0")


_LOAD = "l AS (SELECT gid AS pivot, CAST(coalesce(sum(lo_deg), 0) AS BIGINT) AS load FROM d LEFT JOIN o ON hi = gid GROUP BY gid)"
_FULL = "l AS (SELECT pivot, CAST(sum(l) AS BIGINT) AS load FROM (SELECT gu AS pivot, dv AS l FROM x UNION ALL SELECT gv, du FROM x) GROUP BY pivot)"
_EXACT = "below AS (SELECT g, above, row_number() OVER (PARTITION BY mid ORDER BY gd, g) - 1 AS below FROM n), l AS (SELECT gid AS pivot, CAST(coalesce(sum(below), 0) AS BIGINT) AS load FROM d LEFT JOIN below ON g = gid AND above GROUP BY gid)"
#: Wedges and balanced butterflies by pivot, then by bin of an assignment ``k``.
_BY_PIVOT = f"w AS (SELECT p.g AS pivot, b.g AS fin, sum(CASE WHEN p.sign = b.sign THEN 1 ELSE 0 END) AS b1, sum(CASE WHEN p.sign <> b.sign THEN 1 ELSE 0 END) AS b2 FROM n p JOIN n b ON p.mid = b.mid AND p.above AND (b.gd < p.gd OR (b.gd = p.gd AND b.g < p.g)) GROUP BY 1, 2), y AS (SELECT pivot, sum({_BAL}) AS balanced, sum(b1 + b2) AS wedges FROM w GROUP BY pivot)"


def _per_bin(bins: int) -> str:
    return f"SELECT CAST(b AS INT) AS bin, CAST(coalesce(sum(balanced), 0) AS BIGINT) AS balanced, CAST(coalesce(sum(wedges), 0) AS BIGINT) AS wedges FROM range({bins}) t(b) LEFT JOIN k ON bin = b LEFT JOIN y ON y.pivot = k.pivot GROUP BY b"


def _blocks(bins: int) -> str:
    return f"k AS (SELECT pivot, CAST(floor((row_number() OVER (ORDER BY pivot) - 1) * {bins} / count(*) OVER ()) AS INT) AS bin, load FROM l)"


def _lpt(bins: int, out: str = "k", source: str = "l") -> str:
    return f"{out}_u AS (SELECT pivot AS unit, load FROM {source}), {_greedy(f'{out}_u', bins, f'{out}_g')}, {out} AS (SELECT pivot, bin, load FROM {source} JOIN {out}_g ON unit = pivot)"


def _volume(k: str = "k") -> str:
    """Edges and list entries by bin: a list goes to a bin once, cut at the greatest pivot that needs it."""
    return f"""h AS (SELECT bin, lo AS mid, hi, hi_deg FROM o JOIN {k} ON hi = pivot), a AS (SELECT bin, count(*) AS edges FROM h GROUP BY bin),
top AS (SELECT bin, mid, max({{'d': hi_deg, 'g': hi}}) AS t FROM h GROUP BY bin, mid), b AS (SELECT bin, count(*) AS entries FROM top JOIN n ON n.mid = top.mid AND (n.gd < t.d OR (n.gd = t.d AND n.g < t.g)) GROUP BY bin)"""


def _tip(g: str, side: str) -> str:
    """Tip numbers by taking all vertices at the least level away, over and over."""
    return f"""WITH RECURSIVE {_ctes(g)}, {_pairs(side)}, near AS (SELECT a, b, {_BAL} AS n FROM q WHERE {_BAL} > 0), y AS (SELECT a, b, n FROM near UNION ALL SELECT b, a, n FROM near),
r AS (SELECT DISTINCT CAST({side.lower()} AS BIGINT) AS k, CAST(0 AS BIGINT) AS level, false AS gone FROM e UNION ALL
SELECT k, greatest(level, m), c <= greatest(level, m) FROM (SELECT k, level, c, min(c) OVER () AS m FROM (SELECT x.k, max(x.level) AS level, CAST(coalesce(sum(CASE WHEN z.k IS NOT NULL THEN y.n END), 0) AS BIGINT) AS c
FROM r x LEFT JOIN y ON y.a = x.k LEFT JOIN r z ON z.k = y.b AND NOT z.gone WHERE NOT x.gone GROUP BY x.k))) SELECT k AS key, level AS tip FROM r WHERE gone"""


def _wing(edges: str) -> str:
    """Wing numbers likewise, with the butterflies of what is left counted anew each time."""
    return f"""WITH RECURSIVE {edges}, four AS (SELECT a.u AS u1, c.u AS u2, a.v AS v1, b.v AS v2 FROM e a JOIN e b ON a.u = b.u AND a.v < b.v JOIN e c ON a.v = c.v AND a.u < c.u JOIN e d ON d.u = c.u AND d.v = b.v WHERE (a.sign + b.sign + c.sign + d.sign) % 2 = 0),
r AS (SELECT CAST(u AS BIGINT) AS u, CAST(v AS BIGINT) AS v, CAST(0 AS BIGINT) AS level, false AS gone FROM e UNION ALL
SELECT u, v, greatest(level, m), c <= greatest(level, m) FROM (SELECT u, v, level, c, min(c) OVER () AS m FROM (SELECT x.u, x.v, max(x.level) AS level, count(f.u1) AS c FROM r x LEFT JOIN (
SELECT f.* FROM four f JOIN r a ON a.u = u1 AND a.v = v1 AND NOT a.gone JOIN r b ON b.u = u1 AND b.v = v2 AND NOT b.gone JOIN r c ON c.u = u2 AND c.v = v1 AND NOT c.gone JOIN r d ON d.u = u2 AND d.v = v2 AND NOT d.gone) f
ON x.u IN (f.u1, f.u2) AND x.v IN (f.v1, f.v2) WHERE NOT x.gone GROUP BY x.u, x.v))) SELECT u, v, level AS wing FROM r WHERE gone"""


_QUANTITIES = "l AS (SELECT CAST(l_quantity AS BIGINT) AS pivot, count(*) AS load FROM lineitem WHERE l_quantity IS NOT NULL GROUP BY 1)"


def _lines_of(quantity: int) -> str:
    return f"{_RAW['g1']} WHERE l_quantity = {quantity}"


def _assignments(r: _Registry) -> None:
    def work(x: SignedGraph) -> DataFrame:
        return index.workload(x, "restricted")

    for g in ("g1", "g6"):
        base = f"{_ctes(g)}, {_PRIO}, {_LOAD}"
        hashed = f"k AS (SELECT pivot, {_owner('pivot', 8)} AS bin, load FROM l)"
        r.add(f"assign_blocks_{g}", _on(g, lambda x: assign.assign_blocks(work(x), 8)), f"WITH {base}, {_blocks(8)} SELECT pivot, bin, load FROM k")
        r.add(f"assign_hash_{g}", _on(g, lambda x: assign.assign_hash(work(x), 8)), f"WITH {base}, {hashed} SELECT pivot, bin, load FROM k")
        stats = "s AS (SELECT b AS bin, coalesce(sum(load), 0) AS load FROM range(8) t(b) LEFT JOIN k ON bin = b GROUP BY b) SELECT CAST(min(load) AS BIGINT) AS least, CAST(max(load) AS BIGINT) AS greatest, round(max(load) / nullif(min(load), 0), 6) AS ratio FROM s"
        r.add(f"assign_stats_{g}", _on(g, lambda x: assign.assignment_stats(assign.assign_blocks(work(x), 8), 8)), f"WITH {base}, {_blocks(8)}, {stats}")
        r.add(f"assign_lpt_stats_{g}", _on(g, lambda x: assign.assignment_stats(assign.assign_lpt(work(x), 8), 8)), f"WITH RECURSIVE {base}, {_lpt(8)}, {stats}")
        snake = f"WITH {_ctes(g)}, {_PRIO}, {_LOAD}, k AS (SELECT pivot, load, row_number() OVER (ORDER BY load DESC, pivot) - 1 AS i FROM l) SELECT pivot, CAST(CASE WHEN (i // 8) % 2 = 0 THEN i % 8 ELSE 7 - i % 8 END AS INT) AS bin, load FROM k"
        r.add(f"assign_snake_{g}", _on(g, lambda x: assign.assign_snake(work(x), 8)), snake)
        for name, k in (("blocks", _blocks(8)), ("hash", hashed)):
            r.add(f"per_bin_counts_{name}_{g}", _on(g, lambda x, a=name: count.count_pivot_local(x, assigner=a, workload="restricted", return_="bins", max_load=WHOLE).select("bin", "balanced", "wedges")), f"WITH {base}, {k}, {_BY_PIVOT} {_per_bin(8)}")
            r.add(f"exchange_volume_{name}_{g}", _on(g, lambda x, a=name: metrics.exchange_volume(x, assign.ASSIGNERS[a](work(x), 8))), f"WITH {base}, {k}, {_volume()} SELECT a.bin, CAST(edges AS BIGINT) AS edges, CAST(coalesce(entries, 0) AS BIGINT) AS entries, CAST(edges * 17 + coalesce(entries, 0) * 8 AS BIGINT) AS bytes FROM a LEFT JOIN b ON a.bin = b.bin")
        r.add(f"per_bin_counts_lpt_{g}", _on(g, lambda x: count.count_pivot_local(x, assigner="lpt", workload="restricted", form="arrow", return_="bins", max_load=WHOLE).select("bin", "balanced", "wedges")), f"WITH RECURSIVE {base}, {_lpt(8)}, {_BY_PIVOT} {_per_bin(8)}")
        r.add(f"assign_lpt_{g}", _on(g, lambda x: assign.assign_lpt(work(x), 8)), f"WITH RECURSIVE {base}, {_lpt(8)} SELECT pivot, bin, load FROM k")
        units = f"z AS (SELECT pivot, load, CASE WHEN load > 0.25 * (SELECT sum(load) / 8 FROM l) THEN pivot ELSE -1 - {_owner('pivot', 512)} END AS unit FROM l), zu AS (SELECT unit, CAST(sum(load) AS BIGINT) AS load FROM z GROUP BY unit)"
        r.add(f"assign_lpt_scalable_{g}", _on(g, lambda x: assign.assign_lpt_scalable(work(x), 8)), f"WITH RECURSIVE {base}, {units}, {_greedy('zu', 8, 'zg')} SELECT pivot, bin, load FROM z JOIN zg ON z.unit = zg.unit")
    for name, cols in (("lineitem", ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")), ("events", ("event_id", "user_id", "event_type"))):
        text = ", ".join(f"coalesce(CAST({c} AS VARCHAR), '')" for c in cols)
        r.add(f"load_audit_{name}", lambda s, d, n=name, c=cols: ingest_audit(table(s, d, n), c).select("n_rows", "checksum", "files"), f"SELECT count(*) AS n_rows, CAST(sum(CAST(CAST('0x' || substr(md5(concat_ws('|', {text})), 1, 12) AS BIGINT) AS DECIMAL(38, 0))) AS VARCHAR) AS checksum, CAST(1 AS BIGINT) AS files FROM {name}")
    r.add("lpt_example", lambda s, d: assign.assign_lpt(graphs.quantity_loads(s, d), 3).select(F.col("pivot").alias("item"), "bin", "load"), f"WITH RECURSIVE {_QUANTITIES}, {_lpt(3)} SELECT pivot AS item, bin, load FROM k")
    r.add("biclique_g7", _on("g7", lambda x: x.spark.createDataFrame([(measures.is_biclique(x, [0, 1, 2], list(range(64))), measures.is_biclique(x, [0], [64]))], "inside boolean, outside boolean")), f"WITH {_ctes('g7')} SELECT count(*) FILTER (u IN (0, 1, 2)) = 192 AS inside, count(*) FILTER (u = 0 AND v = 64) = 1 AS outside FROM e")
    r.add("tip_w2", lambda s, d: measures.tip_decomposition(graphs.lines_of(s, d, 1)), _tip("g1", "U").replace(_RAW["g1"], _lines_of(1)))
    r.add("wing_w2", lambda s, d: measures.wing_decomposition(graphs.lines_of(s, d, 1)), _wing(_ctes("g1").replace(_RAW["g1"], _lines_of(1))))
    for g, side in (("g5", "U"), ("g5", "V"), ("g6", "U"), ("g6", "V")):
        r.add(f"tip_{side}_{g}", _on(g, lambda x, s=side: measures.tip_decomposition(x, s)), _tip(g, side))


def _experiments(r: _Registry) -> None:
    """The experiments' results that do not depend on the machine, on small grids."""
    only, x = experiments.deterministic, experiments
    union = " UNION ALL ".join
    bal = lambda e, g, c, sql=None, m=("balanced",): _melt(e, g, c, sql or _bbf(g), m)
    columns = ("n_u", "n_v", "n_e", "density", "negatives", "max_deg_u", "max_deg_v", "wedges_u_ends", "wedges_v_ends", "balanced")
    r.add("x1_profile_table", lambda s, d: x.profile_table(s, d, ALL), union(_melt("profile_table", g, "-", r.sql[f"profile_{g}"], columns) for g in ALL))
    bounds = lambda g: f"SELECT sum_min FROM ({r.sql[f'work_bounds_{g}']})"
    r.add("x2_compare_counters", lambda s, d: only(x.compare_counters(s, d, ("g1", "g5", "g6"))), union([*(bal("compare_counters", g, m) for g in ("g1", "g5", "g6") for m in ("serial", "shared", "pivot_local")), *(_melt("compare_counters", g, "all", bounds(g), ("sum_min",)) for g in ("g1", "g5", "g6"))]))
    blind = lambda g: _melt("compare_baseline", g, "signblind", r.sql[f"bbf_signblind_{g}"], ("total", "balanced", "wasted"))
    r.add("x3_compare_baseline", lambda s, d: only(x.compare_baseline(s, d, ("g5", "g6"))), union([*(bal("compare_baseline", g, "pivot_local") for g in ("g5", "g6")), *(blind(g) for g in ("g5", "g6"))]))
    r.add("x4_phase_breakdown", lambda s, d: only(x.phase_breakdown(s, d, ("g6",), (1, 4))).where("metric = 'balanced'"), union(bal("phase_breakdown", "g6", c) for c in ("1x12", "4x3")))
    lpt = lambda load, bins: f"WITH RECURSIVE {_ctes('g6')}, {_PRIO}, {load}, {_lpt(bins)}"
    ratio = lambda bins: f"{_BY_PIVOT}, s AS ({_per_bin(bins)}) SELECT max(wedges) / nullif(min(wedges), 0) AS straggler_wedges FROM s"
    r.add("x6_straggler_grid", lambda s, d: x.straggler_grid(s, d, ("g6",), (2, 4), "restricted"), union(_melt("straggler_grid", "g6", str(b), f"{lpt_scalable(b)}, {ratio(b)}", ("straggler_wedges",)) for b in (2, 4)))
    r.add("x7_volume_vs_bins", lambda s, d: only(x.volume_vs_bins(s, d, ("g6",), (1, 2, 4))), union(_melt("volume_vs_bins", "g6", str(b), f"{lpt(_FULL, b)}, {_volume()} SELECT sum(edges * 17 + coalesce(entries, 0) * 8) AS bytes FROM a LEFT JOIN b ON a.bin = b.bin", ("bytes",)) for b in (1, 2, 4)))
    r.add("x9_flat_vs_hybrid", lambda s, d: only(x.flat_vs_hybrid(s, d, ("g6",))), union(bal("flat_vs_hybrid", "g6", c) for c in ("hybrid", "flat")))
    ablation = [("blocks", f"WITH {_ctes('g6')}, {_PRIO}, {_FULL}, {_blocks(4)}"), *((f"lpt_{n}", lpt(load, 4)) for n, load in (("full", _FULL), ("restricted", _LOAD), ("exact", _EXACT)))]
    r.add("x10_partitioning_ablation", lambda s, d: x.partitioning_ablation(s, d, ("g6",), 4).where("metric = 'straggler_wedges'"), union(_melt("partitioning_ablation", "g6", c, f"{head}, {_BY_PIVOT}, s AS ({_per_bin(4)}) SELECT coalesce(max(wedges) / nullif(min(wedges), 0), CAST('inf' AS DOUBLE)) AS straggler_wedges FROM s", ("straggler_wedges",)) for c, head in ablation))
    sweep = lambda n: f"SELECT balanced FROM ({r.sql['sign_sweep_g1']}) WHERE neg_pct = {n}"
    r.add("x11_sign_distribution", lambda s, d: only(x.sign_distribution(s, d, ("g1",), (30, 50))), union(bal("sign_distribution", "g1", f"neg{n}", sweep(n)) for n in (30, 50)))
    r.add("x12_class_separation", lambda s, d: only(x.class_separation(s, d)), union(bal("class_separation", g, c) for g in ("g5", "g6") for c in ("separated", "not_separated")))
    split = [_melt("applications", g, f"ends_{e}", r.sql[f"class_split_{e}_{g}"], ("symmetric", "asymmetric")) for g in ("g5",) for e in "UV"]
    tips = _melt("applications", "g5", "U", f"SELECT max(tip) AS max_tip FROM ({_tip('g5', 'U')})", ("max_tip",))
    r.add("x14_applications", lambda s, d: only(x.applications(s, d, ("g5",))).where("graph = 'g5'"), union([*split, tips]))
    part = lambda q: _melt("worked_examples", f"lines_of_{q}", "-", f"SELECT balanced, total FROM ({r.sql['balance_summary_g1'].replace(_RAW['g1'], _lines_of(q))})", ("balanced", "total"))
    ratio = lambda c, k: _melt("worked_examples", "loads", c, f"{k}, s AS (SELECT coalesce(sum(load), 0) AS load FROM range(3) t(b) LEFT JOIN k ON bin = b GROUP BY b) SELECT CAST(max(load) AS DOUBLE) / nullif(min(load), 0) AS ratio FROM s", ("ratio",))
    r.add("x13_worked_examples", lambda s, d: x.worked_examples(s, d), union([*map(part, (1, 2, 3, 4, 5)), ratio("greedy", f"WITH RECURSIVE {_QUANTITIES}, {_lpt(3)}"), ratio("blocks", f"WITH {_QUANTITIES}, {_blocks(3)}")]))


def lpt_scalable(bins: int) -> str:
    """The two-level assignment of g6 as a table ``k``."""
    units = f"z AS (SELECT pivot, load, CASE WHEN load > 0.25 * (SELECT sum(load) / {bins} FROM l) THEN pivot ELSE -1 - {_owner('pivot', 64 * bins)} END AS unit FROM l), zu AS (SELECT unit, CAST(sum(load) AS BIGINT) AS load FROM z GROUP BY unit)"
    return f"WITH RECURSIVE {_ctes('g6')}, {_PRIO}, {_LOAD}, {units}, {_greedy('zu', bins, 'zg')}, k AS (SELECT pivot, bin, load FROM z JOIN zg ON z.unit = zg.unit)"


def _relational(r: _Registry) -> None:
    def pair_table(x: SignedGraph) -> DataFrame:
        return count.pairs(x, "V").select(F.shiftright("end", 1).alias("a"), F.shiftright("pivot", 1).alias("b"), "b1", "b2")

    def snapshots(spark: SparkSession, sf: str) -> DataFrame:
        rows = graphs.interactions(spark, sf, "g1")
        old = pair_table(SignedGraph(ingest.sign_as_of(rows, F.lit("1996-01-01").cast("timestamp"))))
        new = pair_table(SignedGraph(ingest.resolve_conflicts(rows)))
        both = old.select("a", "b", F.col("b1").alias("o1"), F.col("b2").alias("o2")).join(new, ["a", "b"], "full")
        moved = ~(F.col("o1").eqNullSafe(F.col("b1")) & F.col("o2").eqNullSafe(F.col("b2")))
        return both.where(moved).agg(F.count(F.lit(1)).alias("changed"), F.sum(F.when(F.col("o1").isNull(), 1).otherwise(0)).cast("long").alias("added"))

    def at(when: str) -> str:
        return f"SELECT u, v, arg_max(sign, (ts, k1, k2, sign)) AS sign FROM raw WHERE ts <= TIMESTAMP '{when}' GROUP BY u, v"

    pair_sql = lambda e: f"SELECT x.v AS a, y.v AS b, sum(CASE WHEN x.sign = y.sign THEN 1 ELSE 0 END) AS b1, sum(CASE WHEN x.sign <> y.sign THEN 1 ELSE 0 END) AS b2 FROM {e} x JOIN {e} y ON x.u = y.u AND x.v < y.v GROUP BY 1, 2"
    r.add("snapshot_diff_g1", snapshots, f"WITH {_ctes('g1')}, e0 AS ({at('1996-01-01 00:00:00')}), o AS ({pair_sql('e0')}), n AS ({pair_sql('e')}) SELECT count(*) AS changed, CAST(coalesce(sum(CASE WHEN o.a IS NULL THEN 1 ELSE 0 END), 0) AS BIGINT) AS added FROM o FULL JOIN n ON o.a = n.a AND o.b = n.b WHERE o.b1 IS DISTINCT FROM n.b1 OR o.b2 IS DISTINCT FROM n.b2")
    r.add("as_of_g1", lambda s, d: ingest.sign_as_of(graphs.interactions(s, d, "g1"), F.lit("1995-06-30").cast("timestamp")).select("u", "v", F.col("sign").cast("int").alias("sign")), f"WITH {_ctes('g1')} SELECT u, v, CAST(arg_max(sign, (ts, k1, k2, sign)) AS INT) AS sign FROM raw WHERE ts <= TIMESTAMP '1995-06-30 00:00:00' GROUP BY u, v")

    def cube(spark: SparkSession, sf: str) -> DataFrame:
        who = table(spark, sf, "customer").select(F.col("c_custkey").alias("u"), F.col("c_nationkey").alias("nation"), F.col("c_mktsegment").alias("segment"))
        e = graphs.build(spark, sf, "g3").edges.join(who, "u")
        return e.cube("nation", "segment", F.col("sign").cast("int").alias("sign")).agg(F.count(F.lit(1)).alias("edges"))

    r.add("cube_signed_degree", cube, f"WITH {_ctes('g3')} SELECT c_nationkey AS nation, c_mktsegment AS segment, CAST(sign AS INT) AS sign, count(*) AS edges FROM e JOIN customer ON u = c_custkey GROUP BY CUBE (c_nationkey, c_mktsegment, sign)")

    def induced(spark: SparkSession, sf: str) -> DataFrame:
        keep = table(spark, sf, "customer").where("c_mktsegment = 'BUILDING'").select(F.col("c_custkey").alias("u"))
        g = graphs.build(spark, sf, "g2")
        return count.count_wedge_agg(SignedGraph(g.edges.join(keep, "u", "left_semi").select("u", "v", "sign")), "V")

    r.add("bbf_induced_g2", induced, f"WITH {_ctes('g2').replace('e AS (SELECT', 'e0 AS (SELECT', 1)}, e AS (SELECT e0.* FROM e0 JOIN customer ON u = c_custkey WHERE c_mktsegment = 'BUILDING'), {_pairs('V')} SELECT {_sum(_BAL, 'balanced')} FROM q")
    r.add("bbf_negative_only_g1", _on("g1", lambda x: count.count_wedge_agg(x.filtered("sign = 0"), "V")), f"WITH {_ctes('g1').replace('e AS (SELECT', 'e0 AS (SELECT', 1)}, e AS (SELECT * FROM e0 WHERE sign = 0), {_pairs('V')} SELECT {_sum(_BAL, 'balanced')} FROM q")

    day = "date_trunc('day', ts)"
    daily = f"WITH raw AS ({_RAW['g6']}), e AS (SELECT {day} AS d, u, v, arg_max(sign, (ts, k1, k2, sign)) AS sign FROM raw GROUP BY 1, 2, 3), p AS (SELECT x.d, x.v AS a, y.v AS b, sum(CASE WHEN x.sign = y.sign THEN 1 ELSE 0 END) AS b1, sum(CASE WHEN x.sign <> y.sign THEN 1 ELSE 0 END) AS b2 FROM e x JOIN e y ON x.d = y.d AND x.u = y.u AND x.v < y.v GROUP BY 1, 2, 3) SELECT strftime(d, '%Y-%m-%d') AS day, CAST(sum({_BAL}) AS BIGINT) AS balanced FROM p GROUP BY d"
    as_day = lambda d: d.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "balanced")
    r.add("window_bbf_daily", lambda s, d: as_day(streaming.windowed_counts(streaming.windowed_graphs(streaming.event_edges(table(s, d, "events"))))), daily)
    r.add("stream_window_bbf", lambda s, d: as_day(streaming.windowed_counts(streaming.replay(s, f"{d}/events.parquet*", lambda e: streaming.windowed_graphs(e)))), daily)
    r.add("stream_latest_sign", lambda s, d: streaming.replay(s, f"{d}/events.parquet*", streaming.latest_signs).select("u", "v", F.col("sign").cast("int").alias("sign")), f"WITH {_ctes('g6')} SELECT u, v, CAST(sign AS INT) AS sign FROM e")


    def by_window(cut: str, rows: str) -> str:
        return f"WITH raw AS ({_RAW['g6']}), w AS ({rows}), e AS (SELECT d, u, v, arg_max(sign, (ts, k1, k2, sign)) AS sign FROM w GROUP BY 1, 2, 3), p AS (SELECT x.d, x.v AS a, y.v AS b, sum(CASE WHEN x.sign = y.sign THEN 1 ELSE 0 END) AS b1, sum(CASE WHEN x.sign <> y.sign THEN 1 ELSE 0 END) AS b2 FROM e x JOIN e y ON x.d = y.d AND x.u = y.u AND x.v < y.v GROUP BY 1, 2, 3) SELECT strftime(d, '{cut}') AS start, CAST(sum({_BAL}) AS BIGINT) AS balanced FROM p GROUP BY d"

    told = lambda d: d.select(F.date_format("start", "yyyy-MM-dd HH:mm").alias("start"), "balanced")
    events = lambda s, d: streaming.event_edges(table(s, d, "events"))
    slid = "SELECT raw.*, date_trunc('day', ts) - CASE k WHEN 1 THEN INTERVAL 1 DAY ELSE INTERVAL 0 DAY END AS d FROM raw, range(2) t(k)"
    r.add("window_bbf_sliding", lambda s, d: told(streaming.windowed_counts(streaming.windowed_graphs(events(s, d), "2 days", "1 day"))), by_window("%Y-%m-%d %H:%M", slid))
    session = "SELECT raw.*, start AS d FROM raw JOIN (SELECT m, min(m) OVER (PARTITION BY session) AS start FROM (SELECT m, sum(fresh) OVER (ORDER BY m) AS session FROM (SELECT m, CASE WHEN m - lag(m) OVER (ORDER BY m) <= INTERVAL 180 MINUTE THEN 0 ELSE 1 END AS fresh FROM (SELECT DISTINCT date_trunc('minute', ts) AS m FROM raw)))) z ON z.m = date_trunc('minute', raw.ts)"
    r.add("window_bbf_session", lambda s, d: told(streaming.windowed_counts(streaming.session_windows(events(s, d), 180))), by_window("%Y-%m-%d %H:%M", session))
    last = lambda: F.max_by("sign", "batch").cast("int").alias("sign")
    r.add("stream_latest_state", lambda s, d: streaming.replay(s, f"{d}/events.parquet*", streaming.latest_signs_state, "update").groupBy("u", "v").agg(last()), f"WITH {_ctes('g6')} SELECT u, v, CAST(sign AS INT) AS sign FROM e")
    r.add("stream_without_replays", lambda s, d: streaming.replay(s, f"{d}/events.parquet*", lambda e: streaming.without_replays(e).select("event_id", "u", "v"), "append").select("event_id", "u", "v"), f"WITH raw AS ({_RAW['g6']}) SELECT DISTINCT k1 AS event_id, u, v FROM raw WHERE u IS NOT NULL AND v IS NOT NULL")


def _around(r: _Registry) -> None:
    def two(s: SparkSession, d: str) -> tuple[SignedGraph, SignedGraph]:
        rows = graphs.interactions(s, d, "g1")
        return tuple(SignedGraph(ingest.sign_as_of(rows, F.lit(t).cast("timestamp"))) for t in ("1995-07-01", "1996-07-01"))

    state = lambda n, t: f"e{n} AS (SELECT u, v, arg_max(sign, (ts, k1, k2, sign)) AS sign FROM raw WHERE ts <= TIMESTAMP '{t} 00:00:00' GROUP BY u, v)"
    both = f"WITH {_ctes('g1')}, {state(0, '1995-07-01')}, {state(1, '1996-07-01')}"
    plain = lambda d: d.select("u", "v", F.col("sign").cast("int").alias("sign"))
    r.add("snapshot_kept_g1", lambda s, d: plain(relational.kept_edges(*two(s, d))), f"{both} SELECT u, v, CAST(sign AS INT) AS sign FROM (SELECT * FROM e0 INTERSECT SELECT * FROM e1)")
    r.add("snapshot_changed_g1", lambda s, d: plain(relational.changed_edges(*two(s, d))), f"{both} SELECT u, v, CAST(sign AS INT) AS sign FROM (SELECT * FROM e1 EXCEPT ALL SELECT * FROM e0)")
    r.add("snapshot_lost_g1", lambda s, d: relational.lost_edges(two(s, d)[1], two(s, d)[0]), f"{both} SELECT u, v FROM e1 WHERE NOT EXISTS (SELECT 1 FROM e0 WHERE e0.u = e1.u AND e0.v = e1.v)")
    for g in ("g3", "g6"):
        base = f"WITH {_ctes(g)}, {_PRIO}"
        r.add(f"degree_ranks_{g}", _on(g, relational.degree_ranks), f"{base} SELECT gid, deg, CAST(rank() OVER (PARTITION BY gid % 2 ORDER BY deg DESC) AS INT) AS rank, CAST(dense_rank() OVER (PARTITION BY gid % 2 ORDER BY deg DESC) AS INT) AS dense_rank, CAST(ntile(4) OVER (PARTITION BY gid % 2 ORDER BY deg DESC, gid) AS INT) AS tile FROM d")
        r.add(f"degree_quantiles_{g}", _on(g, relational.degree_quantiles), f"{base} SELECT CAST(gid % 2 AS INT) AS side, quantile_cont(deg, 0.5) AS median, quantile_cont(deg, 0.9) AS p90, max(deg) AS greatest FROM d GROUP BY 1")
        r.add(f"work_cdf_{g}", _on(g, lambda x: relational.work_cdf(index.workload(x))), f"{base}, l AS (SELECT pivot, CAST(sum(l) AS BIGINT) AS load FROM (SELECT gu AS pivot, dv AS l FROM x UNION ALL SELECT gv, du FROM x) GROUP BY pivot) SELECT pivot, load, CAST(sum(load) OVER (ORDER BY load DESC, pivot ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM l")
        r.add(f"sign_pivot_{g}", _on(g, lambda x: relational.sign_pivot(x.edges, "v")), f"WITH {_ctes(g)} SELECT v, count(*) FILTER (sign = 0) AS negative, count(*) FILTER (sign = 1) AS positive FROM e GROUP BY v")
    r.add("moving_positive_g6", lambda s, d: relational.moving_positive(graphs.interactions(s, d, "g6")), f"WITH {_ctes('g6')}, s AS (SELECT *, CAST(floor(epoch(ts)) AS BIGINT) AS sec FROM raw) SELECT u, k1, CAST(sum(sign) OVER w AS BIGINT) AS positive, count(*) OVER w AS n FROM s WINDOW w AS (PARTITION BY u ORDER BY sec RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW)")

    def as_of(s: SparkSession, d: str) -> DataFrame:
        rows = graphs.interactions(s, d, "g1")
        probes = rows.select("u", "v").distinct().withColumn("at", F.lit("1995-06-30").cast("timestamp"))
        return relational.as_of_join(probes, rows).select("u", "v", "sign")

    r.add("as_of_join_g1", as_of, f"WITH {_ctes('g1')}, {state(0, '1995-06-30')} SELECT e.u, e.v, CAST(e0.sign AS INT) AS sign FROM e LEFT JOIN e0 ON e.u = e0.u AND e.v = e0.v")

    def held(s: SparkSession, d: str) -> DataFrame:
        points = s.createDataFrame([(t,) for t in ("1995-03-15", "1996-06-30", "1998-01-01")], "label string").withColumn("at", F.col("label").cast("timestamp"))
        return relational.interval_join(relational.validity(graphs.interactions(s, d, "g1")), points)

    at = " UNION ALL ".join(f"SELECT '{t}' AS label, count(*) AS edges, {_sum('sign', 'positive')} FROM (SELECT u, v, arg_max(sign, (ts, k1, k2, sign)) AS sign FROM raw WHERE ts <= TIMESTAMP '{t} 00:00:00' GROUP BY u, v)" for t in ("1995-03-15", "1996-06-30", "1998-01-01"))
    r.add("interval_join_g1", held, f"WITH {_ctes('g1')} {at}")

    def rolled(s: SparkSession, d: str) -> DataFrame:
        who = table(s, d, "customer").select(F.col("c_custkey").alias("u"), F.col("c_nationkey").alias("nation"), F.col("c_mktsegment").alias("segment"))
        return relational.rollup_degree(graphs.build(s, d, "g3").edges, who, ["nation", "segment"])

    r.add("rollup_degree_g3", rolled, f"WITH {_ctes('g3')} SELECT c_nationkey AS nation, c_mktsegment AS segment, count(*) AS edges, CAST(sum(sign) AS BIGINT) AS positive, CAST(grouping_id(c_nationkey, c_mktsegment) AS INT) AS level FROM e JOIN customer ON u = c_custkey GROUP BY ROLLUP (c_nationkey, c_mktsegment)")


def registry() -> _Registry:
    r = _Registry()
    for part in (_edges, _index, _counts, _assignments, _experiments, _relational, _around):
        part(r)
    return r


def entry(spark: SparkSession, sf: str) -> DataFrame:
    """The pivot-partitioned counter on g1, with per-bin rows."""
    return _narrow(count.count_pivot_local(graphs.build(spark, sf, "g1"), return_="bins"))
