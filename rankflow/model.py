"""Records that the operators pass to each other."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame

DEAD_ENDS = ("selfloop", "teleport", "none")
DISCIPLINES = ("sync", "blocked", "local")


def require_columns(df: DataFrame, columns: Iterable[str]) -> None:
    missing = [c for c in columns if c not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {', '.join(missing)}")


@dataclass(frozen=True)
class Graph:
    """A snapshot: ``vertices(id)``, ``edges(src, dst)`` without repeats, and ``edges_w(src, dst, w)`` with ``w`` one over the out-degree.

    ``in_w`` holds the rows of ``edges_w``, laid out by ``dst``.  ``patches`` counts the
    batches that lie over the written layouts, ``m`` the edges, where it is known.
    """

    vertices: DataFrame
    edges: DataFrame
    edges_w: DataFrame
    n: int
    dead_ends: str = "selfloop"
    in_w: DataFrame | None = None
    patches: int = 0
    m: int | None = None

    @property
    def by_dst(self) -> DataFrame:
        return self.edges_w if self.in_w is None else self.in_w

    @property
    def id_type(self):
        return self.vertices.schema["id"].dataType


@dataclass(frozen=True)
class Batch:
    """Edges to insert and to delete, both ``(src, dst)``."""

    ins: DataFrame
    dels: DataFrame

    def changed(self) -> DataFrame:
        return self.ins.select("src", "dst").union(self.dels.select("src", "dst"))

    def signed(self) -> DataFrame:
        """``(src, dst, op)`` with ``op`` one of ``+`` and ``-``."""
        return self.ins.selectExpr("src", "dst", "'+' AS op").union(self.dels.selectExpr("src", "dst", "'-' AS op"))

    @staticmethod
    def of(signed: DataFrame) -> Batch:
        require_columns(signed, ("src", "dst", "op"))
        return Batch(signed.where("op = '+'").select("src", "dst"), signed.where("op = '-'").select("src", "dst"))


@dataclass(frozen=True)
class Params:
    """Damping, tolerances and how an iteration runs; the defaults are the paper's."""

    alpha: float = 0.85
    tau: float = 1e-10
    tau_f: float | None = None
    tau_f_divisor: float = 1e5
    max_iter: int = 500
    dead_ends: str = "selfloop"
    discipline: str = "sync"
    blocks: int = 2
    inner: int = 4
    snapshots: str = "union"
    #: False: run ``max_iter`` rounds whatever the change.
    stop: bool = True
    #: Steps of full methods between written tables; each is tested for convergence.
    write_every: int = 1

    def __post_init__(self) -> None:
        if self.dead_ends not in DEAD_ENDS:
            raise ValueError(f"dead_ends is one of {DEAD_ENDS}")
        if self.discipline not in DISCIPLINES:
            raise ValueError(f"discipline is one of {DISCIPLINES}")

    @property
    def frontier_tolerance(self) -> float:
        return self.tau / self.tau_f_divisor if self.tau_f is None else self.tau_f

    @classmethod
    def temporal(cls, **other) -> Params:
        """A looser frontier tolerance, a tenth of ``tau``, for edges that arrive in time order."""
        return cls(**({"tau_f_divisor": 10.0} | other))

    def but(self, **changes) -> Params:
        return replace(self, **changes)


@dataclass
class RankResult:
    """``ranks(id, rank)``, the ids recomputed, and a row of telemetry for each iteration."""

    ranks: DataFrame
    affected: DataFrame
    iterations: int
    converged: bool
    telemetry: list[dict] = field(default_factory=list)
    seconds_marking: float = 0.0
    seconds_total: float = 0.0
    method: str = ""
    params: Params = field(default_factory=Params)

    @property
    def vertex_updates(self) -> int:
        return sum(t["affected"] for t in self.telemetry)

    @property
    def edges_read(self) -> int:
        """In-edges that were read in all rounds."""
        return sum(t.get("in_edges", 0) for t in self.telemetry)
