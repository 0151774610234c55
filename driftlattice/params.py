"""Parameters of a mining run, checked where they enter."""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace

MICROS = 1_000_000


@dataclass(frozen=True)
class EpisodeSpec:
    """An episode: node labels and, per node, the nodes that must come strictly earlier."""

    kind: str
    nodes: tuple[str, ...]
    preds: tuple[tuple[int, ...], ...]

    @property
    def key(self) -> str:
        return ">".join(self.nodes) if self.kind == "serial" else "+".join(self.nodes) if self.kind == "parallel" else "|".join(f"{x}<{','.join(map(str, p))}" for x, p in zip(self.nodes, self.preds))


def serial(text: str) -> EpisodeSpec:
    """'A>B>C': nodes in strict order."""
    nodes = tuple(text.split(">"))
    if not all(nodes):
        raise ValueError(f"empty node in {text!r}")
    return EpisodeSpec("serial", nodes, tuple(() if k == 0 else (k - 1,) for k in range(len(nodes))))


def parallel(text: str) -> EpisodeSpec:
    """'A+B+C': a multiset without order."""
    nodes = tuple(sorted(text.split("+")))
    if not all(nodes):
        raise ValueError(f"empty node in {text!r}")
    return EpisodeSpec("parallel", nodes, tuple(() for _ in nodes))


def partial(nodes: list[str], edges: list[tuple[str, str]]) -> EpisodeSpec:
    """Any partial order over distinct labels; repeated labels are refused, as greedy counting is not known to be best for them."""
    if len(set(nodes)) != len(nodes):
        raise ValueError("a partial order needs distinct labels")
    place = {x: k for k, x in enumerate(nodes)}
    before: list[set[int]] = [set() for _ in nodes]
    for a, b in edges:
        before[place[b]].add(place[a])
    done: set[int] = set()
    while len(done) < len(nodes):
        ready = {k for k, p in enumerate(before) if k not in done and p <= done}
        if not ready:
            raise ValueError("the order has a cycle")
        done |= ready
    return EpisodeSpec("partial", tuple(nodes), tuple(tuple(sorted(p)) for p in before))


@dataclass(frozen=True)
class MineParams:
    """One mining run. `batch_seconds` is T_b, `m` the batches of a window, `ell` the nodes of an episode."""

    batch_seconds: float = 86_400.0
    m: int = 10
    k: int = 25
    ell: int = 4
    klass: str = "serial"
    relation: str = "contig"
    repeats: bool = True
    delta: float | str = "estimate"
    quantile: float = 0.75
    delta_min: float = 1.0
    delta_first: float = 1.0
    report: str = "tracked"
    missing: str = "zero"
    known: str = "seeded"
    candidates: str = "current"
    slices: int = 1
    max_candidates: int = 2_000_000
    origin: str = "2024-01-01 00:00:00"

    def __post_init__(self):
        if self.m < 1 or self.k < 1 or self.ell < 1 or self.slices < 1 or self.batch_seconds <= 0:
            raise ValueError("m, k, ell and slices start at 1, and a batch has a positive span")
        for name, value, known in (
            ("klass", self.klass, ("serial", "parallel", "itemset")), ("relation", self.relation, ("contig", "subseq")), ("report", self.report, ("tracked", "persistent")),
            ("missing", self.missing, ("zero", "interval")), ("known", self.known, ("frequent", "seeded", "counted")), ("candidates", self.candidates, ("current", "window")),
        ):
            if value not in known:
                raise ValueError(f"{name} is one of {known}, not {value!r}")
        if isinstance(self.delta, str) and self.delta != "estimate":
            raise ValueError("delta is a number or 'estimate'")
        if not 0 <= self.quantile <= 1:
            raise ValueError("a quantile lies between 0 and 1")

    @property
    def span(self) -> int:
        return round(self.batch_seconds * MICROS)

    def with_(self, **changes) -> MineParams:
        return replace(self, **changes)


@dataclass(frozen=True)
class VariantSpec:
    """A way to answer the window query; `v` is the persistence where the variant has one."""

    name: str
    v: float | None = None
    label: str = field(default="", compare=False)

    NAMES = ("window_recount", "batch_union", "sticky_union", "lookahead", "persistent_depth", "heuristic_depth", "exact_depth", "previous_window")

    def __post_init__(self):
        if self.name not in self.NAMES:
            raise ValueError(f"unknown variant {self.name!r}")
        if self.name in ("persistent_depth", "heuristic_depth") and self.v is None:
            raise ValueError(f"{self.name} needs v")

    def checked(self, m: int) -> VariantSpec:
        if self.v is not None and not 1 <= self.v <= m:
            raise ValueError(f"v lies between 1 and m = {m}, not {self.v}")
        return self

    def hits(self) -> int:
        """Batches in which a persistent pattern is in the top k: whole, so rounded up."""
        return math.ceil(self.v or 1)
