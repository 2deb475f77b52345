"""Registry of queries and oracles, and the SQL that oracles share."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.hashing import dyadic_weight_sql, portable_hash_sql

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}
#: Parts and seed of the registered queries; size of the generated network.
P, SEED = 4, 42
RADIX = (256, 6, 16)  # neurons, layers, degree


def query(name: str, oracle: str | None = None):
    def put(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return put


def r6(c) -> Column:
    return F.round(c, 6)


H = portable_hash_sql

TRADE_EDGES = """SELECT 1 AS layer, l_partkey AS "row", o_custkey AS col FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 2, 3
UNION ALL SELECT 2, l_suppkey, l_partkey FROM lineitem GROUP BY 2, 3
UNION ALL SELECT 3, s_nationkey::BIGINT, s_suppkey FROM supplier
UNION ALL SELECT 4, n_regionkey::BIGINT, n_nationkey::BIGINT FROM nation"""
TRADE = f'te AS ({TRADE_EDGES}), tw AS (SELECT layer, "row", col, {dyadic_weight_sql("layer", chr(34) + "row" + chr(34), "col")} AS w FROM te)'
TRADE_NEURONS = """tn AS (SELECT 0 AS layer, c_custkey AS neuron FROM customer UNION ALL SELECT 1, p_partkey FROM part UNION ALL SELECT 2, s_suppkey FROM supplier
UNION ALL SELECT 3, n_nationkey::BIGINT FROM nation UNION ALL SELECT 4, r_regionkey::BIGINT FROM region)"""
MONTH = "((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1)::BIGINT"
TRADE_X = f"tx AS (SELECT DISTINCT {MONTH} AS vec_id, o_custkey AS neuron, 1.0::DOUBLE AS x FROM orders)"
TRADE_Y = f"""ty AS (SELECT vec_id, neuron, 1.0::DOUBLE AS y FROM (SELECT {MONTH} AS vec_id, n_regionkey::BIGINT AS neuron, count(*) AS n, sum(count(*)) OVER (PARTITION BY {MONTH}) AS total
FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2) WHERE 5 * n > total)"""


def radix_sql(neurons: int, layers: int, degree: int, name: str = "rw") -> str:
    from ..sources.generators import strides

    steps = strides(neurons, degree)
    ks = ", ".join(f"({k + 1}, {steps[k % len(steps)]})" for k in range(layers))
    return f"""{name} AS (SELECT layer, "row", col, {dyadic_weight_sql('layer', chr(34) + 'row' + chr(34), 'col')} AS w FROM (SELECT k.layer, r.range AS "row", (r.range + n.range * k.stride) % {neurons} AS col
FROM (VALUES {ks}) AS k(layer, stride), range({neurons}) r, range({degree}) n))"""


def parts_sql(edges: str, neurons: str, p: int = P, name: str = "pt") -> str:
    """Random parts with the inputs' owners: most pins, ties to the lowest."""
    return f"""pr AS (SELECT layer, neuron, ({H('layer', 'neuron', SEED)} % {p})::INTEGER AS part FROM {neurons} WHERE layer > 0),
po AS (SELECT col AS neuron, part FROM (SELECT e.col, p.part, row_number() OVER (PARTITION BY e.col ORDER BY count(*) DESC, p.part) AS nth
FROM {edges} e JOIN pr p ON p.layer = 1 AND p.neuron = e."row" WHERE e.layer = 1 GROUP BY e.col, p.part) WHERE nth = 1),
{name} AS (SELECT layer, neuron, part FROM pr UNION ALL SELECT 0, n.neuron, coalesce(po.part, ({H(0, 'n.neuron', SEED)} % {p})::INTEGER) FROM {neurons} n LEFT JOIN po USING (neuron) WHERE n.layer = 0)"""


def routes_sql(edges: str, parts: str = "pt", name: str = "rt") -> str:
    return f"""{name} AS (SELECT d.layer, d.neuron, s.part AS src, d.dst FROM (SELECT DISTINCT e.layer, e.col AS neuron, p.part AS dst FROM {edges} e JOIN {parts} p ON p.layer = e.layer AND p.neuron = e."row") d
JOIN {parts} s ON s.layer = d.layer - 1 AND s.neuron = d.neuron)"""


def act_sql(z: str, kind: str) -> str:
    return {"sigmoid": f"1 / (1 + exp(-({z})))", "relu": f"greatest({z}, 0)", "tanh": f"tanh({z})", "identity": z}[kind]


def forward_sql(weights: str, neurons: str, x: str, depth: int, kind: str, bias: str | None = None) -> str:
    """CTEs a1 ... a<depth> (vec_id, neuron, z, x), every neuron for every vector."""
    out, at = [f"vs AS (SELECT DISTINCT vec_id FROM {x})"], x
    for k in range(1, depth + 1):
        b = f" + coalesce((SELECT b FROM {bias} WHERE {bias}.layer = {k} AND {bias}.\"row\" = n.neuron), 0)" if bias else ""
        out.append(
            f'z{k} AS (SELECT a.vec_id, w."row" AS neuron, sum(w.w * a.x) AS z FROM {weights} w JOIN {at} a ON w.col = a.neuron WHERE w.layer = {k} GROUP BY 1, 2), '
            f"a{k} AS (SELECT vec_id, neuron, z, {act_sql('z', kind)} AS x FROM (SELECT v.vec_id, n.neuron, coalesce(z.z, 0){b} AS z FROM {neurons} n CROSS JOIN vs v LEFT JOIN z{k} z ON z.vec_id = v.vec_id AND z.neuron = n.neuron WHERE n.layer = {k}))"
        )
        at = f"a{k}"
    return ", ".join(out)
