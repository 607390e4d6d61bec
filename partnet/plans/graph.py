"""Declarations: networks over variables, bottleneck specifications, the trade-off."""

from __future__ import annotations

import json
import warnings
from dataclasses import dataclass, field


@dataclass(frozen=True)
class Dag:
    """parents[v] in a fixed order; every variable has an entry."""

    parents: dict[str, tuple[str, ...]]

    @classmethod
    def parse(cls, text: str, variables: tuple[str, ...] = ()) -> Dag:
        """Edges as "A->T; T->B", several targets as "T->B,C"; a name alone is a node without edges."""
        found: dict[str, list[str]] = {v: [] for v in variables}
        for part in filter(None, (x.strip() for x in text.replace("\n", ";").split(";"))):
            source, arrow, targets = part.partition("->")
            found.setdefault(source.strip(), [])
            for target in filter(None, (x.strip() for x in targets.split(","))):
                found.setdefault(target, [])
                if source.strip() not in found[target]:
                    found[target].append(source.strip())
            if arrow and not targets.strip():
                raise ValueError(f"edge without a target: {part!r}")
        dag = cls({v: tuple(p) for v, p in found.items()})
        dag.order()
        return dag

    def order(self) -> list[str]:
        """A topological order; raises on a cycle."""
        left, out = dict(self.parents), []
        while left:
            free = [v for v, p in left.items() if not any(x in left for x in p)]
            if not free:
                raise ValueError(f"the network has a cycle among {sorted(left)}")
            out += free
            left = {v: p for v, p in left.items() if v not in free}
        return out

    def children(self, v: str) -> list[str]:
        return [c for c, p in self.parents.items() if v in p]


@dataclass(frozen=True)
class TradeOff:
    """kind "beta" weighs relevance in the first objective, "gamma" in the second; beta = gamma / (1 + gamma)."""

    kind: str
    value: float

    def __post_init__(self):
        if self.kind not in ("beta", "gamma") or not self.value >= 0:
            raise ValueError(f"no such trade-off: {self.kind} {self.value}")

    @classmethod
    def beta(cls, x: float) -> TradeOff:
        return cls("beta", float(x))

    @classmethod
    def gamma(cls, x: float) -> TradeOff:
        return cls("gamma", float(x))

    def to_beta(self) -> float:
        return self.value if self.kind == "beta" else self.value / (1 + self.value)

    def to_gamma(self) -> float:
        if self.kind == "gamma":
            return self.value
        if self.value >= 1:
            raise ValueError("beta of 1 or more has no gamma")
        return self.value / (1 - self.value)


@dataclass(frozen=True)
class BottleneckSpec:
    """Which observed variables each cluster variable compresses, and which relations the clusters must carry."""

    name: str
    observed: tuple[str, ...]
    g_in: Dag
    g_out: Dag
    objective: str = "beta"
    form: str = "collapsed"
    #: sizes per cluster variable are chosen at solving time
    clusters: tuple[str, ...] = field(default=())

    def __post_init__(self):
        clusters = tuple(v for v in self.g_in.parents if v not in self.observed)
        object.__setattr__(self, "clusters", clusters)
        if not clusters:
            raise ValueError("no cluster variable")
        if any(c in p for c in clusters for p in self.g_in.parents.values()):
            raise ValueError("cluster variables are leaves of the compression network")
        if empty := [c for c in clusters if not self.g_in.parents[c]]:
            raise ValueError(f"nothing to compress for {empty}")
        for v in {*self.g_in.parents, *self.g_out.parents} - {*self.observed, *clusters}:
            raise ValueError(f"unknown variable {v}")
        self.g_in.order()
        self.g_out.order()
        for c in clusters:
            if set(self.g_in.parents[c]) & set(self.g_out.parents.get(c, ())):
                warnings.warn(f"{c} compresses one of its own parents in the relevance network", stacklevel=2)

    def sources(self, cluster: str) -> tuple[str, ...]:
        return self.g_in.parents[cluster]

    def to_json(self) -> str:
        return json.dumps({"name": self.name, "observed": self.observed, "g_in": self.g_in.parents, "g_out": self.g_out.parents, "objective": self.objective, "form": self.form, "clusters": self.clusters})

    @classmethod
    def from_json(cls, text: str) -> BottleneckSpec:
        x = json.loads(text)
        dag = lambda d: Dag({k: tuple(v) for k, v in d.items()})
        return cls(x["name"], tuple(x["observed"]), dag(x["g_in"]), dag(x["g_out"]), x["objective"], x["form"])


@dataclass(frozen=True)
class Term:
    """One expected divergence of the distortion: of y given z, between "given u" and "given t"."""

    y: tuple[str, ...]
    z: tuple[str, ...]
    weight: float = 1.0
    kind: str = "child"


def distortion_terms(spec: BottleneckSpec, cluster: str) -> list[Term]:
    """All terms of a cluster variable: each of its children in the relevance network, and its own parents as a block."""
    out = []
    for child, parents in spec.g_out.parents.items():
        if cluster in parents:
            out.append(Term((child,), tuple(p for p in parents if p != cluster), kind="cluster child" if child in spec.clusters else "child"))
    if own := spec.g_out.parents.get(cluster, ()):
        out.append(Term(tuple(own), (), kind="own parents"))
    return out


def collapsed_terms(spec: BottleneckSpec, cluster: str) -> list[Term]:
    """The terms with the compressed variable's own term solved out; the exponent is then gamma.

    Where that variable has further relevance parents z, solving it out leaves the divergence of z with weight -1.
    """
    out, source = [], spec.sources(cluster)
    for term in distortion_terms(spec, cluster):
        if term.y == source and term.kind == "child":
            if term.z:
                out.append(Term(term.z, (), -1.0, "solved out"))
        else:
            out.append(term)
    return out


def has_own_term(spec: BottleneckSpec, cluster: str) -> bool:
    return any(t.kind == "child" and t.y == spec.sources(cluster) for t in distortion_terms(spec, cluster))


def update_rule(spec: BottleneckSpec, cluster: str, trade: TradeOff, form: str | None = None) -> tuple[float, list[Term]]:
    """(exponent, terms) of a cluster's update.

    literal: beta with every term. collapsed: gamma without the own term, where there is one and beta < 1.
    """
    form = form or spec.form
    if form not in ("literal", "collapsed"):
        raise ValueError(f"form is literal or collapsed, not {form!r}")
    if form == "collapsed" and has_own_term(spec, cluster) and (trade.kind == "gamma" or trade.value < 1):
        return trade.to_gamma(), collapsed_terms(spec, cluster)
    return trade.to_beta(), distortion_terms(spec, cluster)
