"""Ready-made specifications. Observed edges of the compression network add constants and are left out."""

from __future__ import annotations

from partnet.plans.graph import BottleneckSpec, Dag


def _spec(name: str, observed: tuple[str, ...], g_in: str, g_out: str, objective: str, form: str = "collapsed") -> BottleneckSpec:
    return BottleneckSpec(name, observed, Dag.parse(g_in, observed), Dag.parse(g_out, observed), objective, form)


def single(a: str, b: str, t: str = "T", objective: str = "beta", target: str = "a") -> BottleneckSpec:
    """One system of clusters of a. target "a": T->b; "b": T->a and T->b. Both pair with either objective."""
    out = f"{t}->{b}" if target == "a" else f"{t}->{a},{b}"
    return _spec(f"single_{objective}_{target}", (a, b), f"{a}->{t}", out, objective)


def parallel(a: str, b: str, r: int = 2, objective: str = "beta", target: str | None = None) -> BottleneckSpec:
    """r systems of clusters of a that together predict b; target "b" also asks them to be independent."""
    names = [f"T{i + 1}" for i in range(r)]
    target = target or ("a" if objective == "beta" else "b")
    goals = b if target == "a" else f"{a},{b}"
    return _spec(f"parallel{r}_{target}", (a, b), f"{a}->{','.join(names)}", "; ".join(f"{t}->{goals}" for t in names), objective, "collapsed" if target == "a" else "literal")


def symmetric(a: str, b: str, target: str = "a") -> BottleneckSpec:
    """Clusters of a and of b. target "a": TA->a, TA->TB, TB->b; "b": both point at both."""
    ta, tb = "TA", "TB"
    out = f"{ta}->{a}; {ta}->{tb}; {tb}->{b}" if target == "a" else f"{ta}->{a},{b}; {tb}->{a},{b}"
    return _spec(f"symmetric_{target}", (a, b), f"{a}->{ta}; {b}->{tb}", out, "gamma", "collapsed" if target == "a" else "literal")


def multi_target(a: str, targets: tuple[str, ...], t: str = "T") -> BottleneckSpec:
    """One system of clusters of a, relevant to several variables."""
    return _spec("multi_target", (a, *targets), f"{a}->{t}", f"{t}->{','.join(targets)}", "beta")


def joint_source(sources: tuple[str, ...], b: str, t: str = "T") -> BottleneckSpec:
    """One system of clusters of value combinations."""
    return _spec("joint_source", (*sources, b), "; ".join(f"{a}->{t}" for a in sources), f"{t}->{b}", "beta")


def custom(observed: tuple[str, ...], g_in: str, g_out: str, objective: str = "beta", form: str = "literal") -> BottleneckSpec:
    return _spec("custom", observed, g_in, g_out, objective, form)


def rescaled_trade(target: str, objective: str, value: float) -> float:
    """The weight at which the plain single bottleneck has the same solutions.

    First objective with the source as a second goal: value / (1 - value); second objective without it: value / (1 + value).
    """
    if objective == "beta" and target == "b":
        if value >= 1:
            raise ValueError("from 1 on the source itself is kept; no plain bottleneck corresponds")
        return value / (1 - value)
    if objective == "gamma" and target == "a":
        return value / (1 + value)
    return value
