"""SQL text for an independent engine: graphs, batches and unrolled steps of the methods.

Each function returns common table expressions; :func:`select` puts them together.
"""

from __future__ import annotations

from rankflow.graphs import SQL
from rankflow.operators.batches import DIGITS

ALPHA = 0.85


def select(parts: list[str], final: str, recursive: bool = False) -> str:
    return f"WITH {'RECURSIVE ' * recursive}{', '.join(parts)} {final}"


def graph(name: str, dead: str = "selfloop") -> list[str]:
    """``e`` raw edges, ``v`` vertices, ``nn`` their number, ``g`` edges, ``w`` weighted edges."""
    loops = " UNION SELECT id, id FROM v" if dead == "selfloop" else ""
    return [
        f"e AS MATERIALIZED (SELECT DISTINCT src, dst FROM ({SQL[name]}))",
        "v AS MATERIALIZED (SELECT DISTINCT id FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e))",
        "nn AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM v)",
        f"g AS MATERIALIZED (SELECT src, dst FROM e{loops})",
        _weights("w", "g"),
    ]


def _weights(name: str, edges: str) -> str:
    return f"{name} AS MATERIALIZED (SELECT src, dst, CAST(1 AS DOUBLE) / count(*) OVER (PARTITION BY src) AS w FROM {edges})"


def _quoted(text: str) -> str:
    return f"'{text}'"


def _drawn(*parts: str) -> str:
    """The number of ``batches.drawn``."""
    return f"CAST('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, {DIGITS}) AS BIGINT)"


def batch(kind: str, size: int | str, seed: int = 1) -> list[str]:
    """``ins`` and ``dels``, drawn and normalised; ``size`` may be an expression; then ``g2`` and ``w2`` after them, ``both`` of old and new edges, and ``so`` the sources."""
    k = f"CAST(round({size} * { {'ins': 1.0, 'del': 0.0, 'mix': 0.8}[kind] }) AS BIGINT)"
    end = lambda side: f"{_drawn(str(seed), 'i', _quoted(side))} % CAST(n AS BIGINT)"
    return [
        "ps AS MATERIALIZED (SELECT id, row_number() OVER (ORDER BY id) - 1 AS pos FROM v)",
        f"dr AS (SELECT {end('src')} AS p, {end('dst')} AS q FROM (SELECT unnest(range({k})) AS i), nn)",
        "ri AS MATERIALIZED (SELECT DISTINCT x.id AS src, y.id AS dst FROM dr JOIN ps x ON x.pos = p JOIN ps y ON y.pos = q WHERE x.id <> y.id)",
        f"rd AS MATERIALIZED (SELECT src, dst FROM (SELECT src, dst, row_number() OVER (ORDER BY {_drawn(str(seed), 'src', 'dst')}, src, dst) AS i FROM g WHERE src <> dst) WHERE i <= {size} - {k})",
        "ins AS MATERIALIZED (SELECT src, dst FROM ri EXCEPT SELECT src, dst FROM g EXCEPT SELECT src, dst FROM rd)",
        "dels AS MATERIALIZED (SELECT src, dst FROM rd EXCEPT SELECT src, dst FROM ri)",
        "g2 AS MATERIALIZED (SELECT src, dst FROM g EXCEPT SELECT src, dst FROM dels UNION SELECT src, dst FROM ins)",
        _weights("w2", "g2"),
        "both2 AS MATERIALIZED (SELECT src, dst FROM g2 UNION SELECT src, dst FROM dels)",
        "so AS MATERIALIZED (SELECT src AS id FROM ins UNION SELECT src FROM dels)",
    ]


def steps(k: int, weights: str, start: str, prefix: str, lost: str = "") -> list[str]:
    """``{prefix}1 .. {prefix}k``: full steps from the table ``start``."""
    out, now = [], start
    for i in range(1, k + 1):
        shared = f" + {ALPHA} * (SELECT coalesce(sum(rank), 0) FROM {now} WHERE id NOT IN (SELECT src FROM {lost})) / n" if lost else ""
        out.append(
            f"{prefix}{i} AS MATERIALIZED (SELECT v.id, {1 - ALPHA} / n + {ALPHA} * coalesce(s, 0){shared} AS rank FROM v CROSS JOIN nn LEFT JOIN "
            f"(SELECT dst AS id, sum(rank * w) AS s FROM {weights} JOIN {now} r ON r.id = src GROUP BY dst) t ON t.id = v.id)"
        )
        now = f"{prefix}{i}"
    return out


def small_graphs(edges: str, k: int) -> list[str]:
    """``y0 .. yk``: steps on many graphs ``graph_id, src, dst`` at once, with loops on all vertices."""
    base = [
        f"e AS MATERIALIZED (SELECT DISTINCT graph_id, src, dst FROM ({edges}))",
        "v AS MATERIALIZED (SELECT *, count(*) OVER (PARTITION BY graph_id) AS n FROM (SELECT DISTINCT graph_id, id FROM (SELECT graph_id, src AS id FROM e UNION ALL SELECT graph_id, dst FROM e)))",
        "w AS MATERIALIZED (SELECT *, CAST(1 AS DOUBLE) / count(*) OVER (PARTITION BY graph_id, src) AS w FROM (SELECT graph_id, src, dst FROM e UNION SELECT graph_id, id, id FROM v))",
        "y0 AS MATERIALIZED (SELECT graph_id, id, CAST(1 AS DOUBLE) / n AS rank, n FROM v)",
    ]
    step = "y{1} AS MATERIALIZED (SELECT r.graph_id, r.id, {2} / r.n + {3} * coalesce(s, 0) AS rank, r.n FROM y{0} r LEFT JOIN (SELECT w.graph_id, dst AS id, sum(rank * w) AS s FROM w JOIN y{0} q ON q.graph_id = w.graph_id AND q.id = src GROUP BY 1, 2) t USING (graph_id, id))"
    return base + [step.format(i, i + 1, 1 - ALPHA, ALPHA) for i in range(k)]


def uniform() -> str:
    return "r0 AS MATERIALIZED (SELECT id, 1 / n AS rank FROM v, nn)"


def restricted(k: int, base: str, marks: str, grows: bool, tau_f: float, blocks: int = 1) -> list[str]:
    """``x1 .. xk`` ranks and ``m1 .. mk`` marks: restricted steps from ranks ``base`` and the marks given."""
    out, now, own = [], base, marks
    n = 0
    for _ in range(k):
        for b in range(blocks):
            n += 1
            some = own if blocks == 1 else f"(SELECT id FROM {own} WHERE id % {blocks} = {b})"
            out.append(
                f"p{n} AS MATERIALIZED (SELECT m.id, {1 - ALPHA} / n + {ALPHA} * coalesce(s, 0) AS rank FROM {some} m CROSS JOIN nn LEFT JOIN "
                f"(SELECT dst AS id, sum(rank * w) AS s FROM w2 JOIN {now} r ON r.id = src WHERE dst IN (SELECT id FROM {some}) GROUP BY dst) t ON t.id = m.id)"
            )
            if grows:
                out.append(
                    f"m{n} AS MATERIALIZED (SELECT id FROM {own} UNION SELECT dst FROM g2 WHERE src IN "
                    f"(SELECT p{n}.id FROM p{n} JOIN {now} r ON r.id = p{n}.id WHERE abs(p{n}.rank - r.rank) > {tau_f!r}))"
                )
                own = f"m{n}"
            out.append(f"x{n} AS MATERIALIZED (SELECT r.id, coalesce(p{n}.rank, r.rank) AS rank FROM {now} r LEFT JOIN p{n} ON p{n}.id = r.id)")
            now = f"x{n}"
    return out


INITIAL = "m0 AS MATERIALIZED (SELECT DISTINCT dst AS id FROM both2 WHERE src IN (SELECT id FROM so))"
REACHED = "rs AS (SELECT dst AS id FROM both2 WHERE src IN (SELECT id FROM so) UNION SELECT b.dst FROM rs JOIN both2 b ON b.src = rs.id)"
P12 = "CAST(round(rank * 1e12) AS BIGINT) AS rank_p12"
