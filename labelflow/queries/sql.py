"""SQL text for DuckDB, apart from the engine: one common table for each step of a method, constants inlined."""

from __future__ import annotations

from ..functions.sketch import SketchSpec
from ..sources.graphs import GEO_BASE
from ..sources.seeds import DRAW_A, DRAW_B, DRAW_P

MU1, MU2, MU3 = 0.98, 0.01, 0.01


def with_(*groups: list[str]) -> str:
    """A WITH clause of lists of 'name AS (...)'; each is computed once."""
    return "WITH " + ",\n".join(t.replace(" AS (", " AS MATERIALIZED (", 1) for g in groups for t in g)


def _draw(per: str) -> str:
    return f"seeds AS (SELECT node, label, 1.0::DOUBLE AS score FROM (SELECT *, row_number() OVER (PARTITION BY label ORDER BY (node * {DRAW_A} + {DRAW_B}) % {DRAW_P}, node) AS r FROM gold) WHERE r <= {per})"


_DICT = ["dict AS (SELECT name, row_number() OVER (ORDER BY name) - 1 AS label FROM (SELECT DISTINCT name FROM members))", "gold AS (SELECT node, label FROM members JOIN dict USING (name))"]

KB = [
    """attrs AS (SELECT p_partkey AS src, 'brand' AS kind, p_brand AS key FROM part UNION ALL SELECT p_partkey, 'type', p_type FROM part
    UNION ALL SELECT p_partkey, 'word1', split_part(p_name, ' ', 1) FROM part UNION ALL SELECT p_partkey, 'word2', split_part(p_name, ' ', 2) FROM part)""",
    "anodes AS (SELECT kind, key, (SELECT max(p_partkey) FROM part) + row_number() OVER (ORDER BY kind, key) AS node FROM (SELECT DISTINCT kind, key FROM attrs))",
    "edges AS (SELECT a.src, n.node AS dst, 1.0::DOUBLE AS w FROM attrs a JOIN anodes n USING (kind, key))",
    "nodes AS (SELECT p_partkey AS node, 'part' AS kind FROM part UNION ALL SELECT node, kind FROM anodes)",
    "members AS (SELECT p_partkey AS node, 'bt|' || p_brand || '|' || p_type AS name FROM part UNION ALL SELECT p_partkey, 'nm|' || p_name FROM part)",
    *_DICT,
    _draw("(SELECT CASE WHEN count(*) < 1000 THEN 1 ELSE 10 END FROM part)"),
]

KB_NOISY = [KB[0].replace(" FROM part)", " FROM part UNION ALL SELECT p_partkey, 'size', p_size::VARCHAR FROM part)") if i == 0 else t for i, t in enumerate(KB)]

GEO = [
    f"""edges AS (SELECT n_nationkey + {GEO_BASE['nation']}::BIGINT AS src, n_regionkey + {GEO_BASE['region']}::BIGINT AS dst, 1.0::DOUBLE AS w FROM nation
    UNION ALL SELECT c_custkey + {GEO_BASE['customer']}, c_nationkey + {GEO_BASE['nation']}, 1.0 FROM customer
    UNION ALL SELECT s_suppkey + {GEO_BASE['supplier']}, s_nationkey + {GEO_BASE['nation']}, 1.0 FROM supplier)""",
    "nodes AS (SELECT src AS node FROM edges UNION SELECT dst FROM edges)",
    f"""members AS (SELECT c_custkey + {GEO_BASE['customer']} AS node, lpad(c_nationkey::VARCHAR, 2, '0') AS name FROM customer
    UNION ALL SELECT s_suppkey + {GEO_BASE['supplier']}, lpad(s_nationkey::VARCHAR, 2, '0') FROM supplier)""",
    *_DICT,
    _draw("10"),
]

def _events(rows: str) -> list[str]:
    return [
        f"rows AS ({rows})",
        "pairs AS (SELECT event_id AS src, 'k' AS kind, json_extract_string(props, '$.k') AS key FROM rows UNION ALL SELECT event_id, 'user', user_id::VARCHAR FROM rows)",
        "anodes AS (SELECT kind, key, (SELECT max(event_id) FROM rows) + row_number() OVER (ORDER BY kind, key) AS node FROM (SELECT DISTINCT kind, key FROM pairs WHERE key IS NOT NULL))",
        "edges AS (SELECT a.src, n.node AS dst, 1.0::DOUBLE AS w FROM pairs a JOIN anodes n USING (kind, key))",
        "nodes AS (SELECT event_id AS node, 'event' AS kind FROM rows UNION ALL SELECT node, kind FROM anodes)",
        "seeds AS (SELECT event_id AS node, row_number() OVER (ORDER BY event_id) - 1 AS label, 1.0::DOUBLE AS score FROM rows)",
    ]


EVENTS = _events("SELECT * FROM events")
FEW_EVENTS = _events("SELECT * FROM events WHERE event_id < 10000")

ORDERS = [
    """links AS (SELECT 'order' AS k1, o_orderkey::VARCHAR AS y1, 'customer' AS k2, o_custkey::VARCHAR AS y2 FROM orders
    UNION ALL SELECT DISTINCT 'order', l_orderkey::VARCHAR, 'part', l_partkey::VARCHAR FROM lineitem
    UNION ALL SELECT DISTINCT 'part', l_partkey::VARCHAR, 'supplier', l_suppkey::VARCHAR FROM lineitem)""",
    "nodes AS (SELECT kind, key, row_number() OVER (ORDER BY kind, key) - 1 AS node FROM (SELECT k1 AS kind, y1 AS key FROM links UNION SELECT k2, y2 FROM links))",
    "edges AS (SELECT a.node AS src, b.node AS dst, 1.0::DOUBLE AS w FROM links JOIN nodes a ON a.kind = k1 AND a.key = y1 JOIN nodes b ON b.kind = k2 AND b.key = y2)",
    "seeds AS (SELECT node, row_number() OVER (ORDER BY node) - 1 AS label, 1.0::DOUBLE AS score FROM nodes WHERE kind = 'order')",
]


def tokens_fixture(table: str, id_sql: str, word: str, name_sql: str, per: int, low: int = 2, share: float = 0.05) -> list[str]:
    return [
        f"raw AS (SELECT {id_sql} AS src, unnest(list_distinct(regexp_extract_all(lower(text), '{word}'))) AS key FROM {table})",
        f"used AS (SELECT key FROM raw GROUP BY key HAVING count(*) BETWEEN {low} AND (SELECT greatest({low}, floor({share}::DOUBLE * count(*) + 1e-9)) FROM {table}))",
        f"anodes AS (SELECT key, (SELECT max({id_sql}) FROM {table}) + row_number() OVER (ORDER BY key) AS node FROM used)",
        "edges AS (SELECT r.src, n.node AS dst, 1.0::DOUBLE AS w FROM raw r JOIN anodes n USING (key))",
        f"nodes AS (SELECT {id_sql} AS node FROM {table} UNION ALL SELECT node FROM anodes)",
        f"members AS (SELECT {id_sql} AS node, {name_sql} AS name FROM {table})",
        *_DICT,
        _draw(str(per)),
    ]


SYM = "sym AS (SELECT src, dst, sum(w) AS w FROM (SELECT src, dst, w FROM edges UNION ALL SELECT dst, src, w FROM edges) WHERE src <> dst GROUP BY 1, 2)"


def ma(seed_mass: str = "1.0") -> list[str]:
    """Modified adsorption: m, coef, fixed."""
    return [
        SYM,
        f"""m AS (SELECT n.node, CASE WHEN s.node IS NULL THEN 0.0 ELSE {seed_mass} END AS s, {MU1} * CASE WHEN s.node IS NULL THEN 0.0 ELSE {seed_mass} END + {MU2} * coalesce(a.a, 0) + {MU3} AS m_vv
        FROM nodes n LEFT JOIN (SELECT dst AS node, sum(w) AS a FROM sym GROUP BY 1) a USING (node) LEFT JOIN (SELECT DISTINCT node FROM seeds) s USING (node))""".replace(f"{MU1} * CASE", f"{MU1}::DOUBLE * CASE").replace(f"+ {MU2} *", f"+ {MU2}::DOUBLE *").replace(f"+ {MU3} AS", f"+ {MU3}::DOUBLE AS"),
        f"coef AS (SELECT src, dst, {MU2}::DOUBLE * w / m_vv AS coef FROM sym JOIN m ON m.node = dst)",
        f"fixed AS (SELECT node, label, {MU1}::DOUBLE * s / m_vv * score AS score FROM seeds JOIN m USING (node))",
    ]


def cells_sql(key: str, spec: SketchSpec) -> str:
    parts = ", ".join(f"({key}::BIGINT * {a} + {b}) % {spec.prime} % {spec.width} + {j * spec.width}" for j, (a, b) in enumerate(zip(spec.a, spec.b)))
    return f"unnest([{parts}])"


def encoded(name: str, of: str, spec: SketchSpec, key: str = "label", val: str = "score", by: str = "node") -> str:
    return f"{name} AS (SELECT {by}, cell, sum(val) AS val FROM (SELECT {by}, {cells_sql(key, spec)} AS cell, {val} AS val FROM {of}) GROUP BY ALL HAVING sum(val) <> 0)"


def iterate(steps: int, key: str = "label", val: str = "score", start: str = "seeds", fixed: str = "fixed", prefix: str = "y", coef: str = "coef") -> list[str]:
    """y0..yT."""
    out = [f"{prefix}0 AS (SELECT node, {key}, {val} FROM {start})"]
    for t in range(1, steps + 1):
        out.append(
            f"{prefix}{t} AS (SELECT node, {key}, sum({val}) AS {val} FROM (SELECT c.dst AS node, y.{key}, c.coef * y.{val} AS {val} FROM {coef} c JOIN {prefix}{t - 1} y ON y.node = c.src"
            f" UNION ALL SELECT node, {key}, {val} FROM {fixed}) GROUP BY 1, 2 HAVING sum({val}) <> 0)"
        )
    return out


def sketched(steps: int, spec: SketchSpec, prefix: str = "s") -> list[str]:
    """The same iteration on cells: q, sfixed, s0..sT."""
    return [encoded("q", "seeds", spec), encoded("sfixed", "fixed", spec), *iterate(steps, "cell", "val", "q", "sfixed", prefix)]


def estimates(name: str, pairs: str, cells: str, spec: SketchSpec) -> str:
    """node, label, estimate for pairs."""
    return f"{name} AS (SELECT p.node, p.label, min(coalesce(c.val, 0.0)) AS estimate FROM (SELECT node, label, {cells_sql('label', spec)} AS cell FROM {pairs}) p LEFT JOIN {cells} c ON c.node = p.node AND c.cell = p.cell GROUP BY 1, 2)"
