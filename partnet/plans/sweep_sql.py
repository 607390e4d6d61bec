"""The same sweeps as a chain of SQL blocks in the long form, for engines that hold the results against ours."""

from __future__ import annotations

from partnet.plans.graph import BottleneckSpec, TradeOff, update_rule

TINY = "1e-300"


class SweepScript:
    """Builds WITH blocks; `current` names the block that holds each cluster variable's table (sources, t, q)."""

    def __init__(self, spec: BottleneckSpec, sizes: dict[str, int], joint_sql: str):
        self.spec, self.sizes, self.blocks, self.n = spec, sizes, [], 0
        seen = ", ".join(spec.observed)
        self.joint = self.add(f"SELECT {seen}, SUM(p) AS p FROM ({joint_sql}) GROUP BY {seen}", "j")
        self.mass = {t: self.add(f"SELECT {self.cols(spec.sources(t))}, SUM(p) AS pu FROM {self.joint} GROUP BY {self.cols(spec.sources(t))}", "mu") for t in spec.clusters}
        self.current = {t: self.start(t) for t in spec.clusters}

    @staticmethod
    def cols(names, table: str = "") -> str:
        return ", ".join(f"{table}.{n}" if table else n for n in names)

    def add(self, sql: str, label: str) -> str:
        self.n += 1
        name = f"{label}_{self.n}"
        self.blocks.append(f"{name} AS MATERIALIZED ({sql})")
        return name

    def start(self, t: str) -> str:
        k, u = self.sizes[t], self.cols(self.spec.sources(t))
        if k == 1:
            return self.add(f"SELECT {u}, 0 AS t, 1.0::DOUBLE AS q FROM {self.mass[t]}", "q")
        return self.add(
            f"SELECT {u}, r.t AS t, CASE WHEN r.t = i % {k} THEN 0.7::DOUBLE ELSE 0.3::DOUBLE / {k - 1} END AS q "
            f"FROM (SELECT {u}, row_number() OVER (ORDER BY {u}) - 1 AS i FROM {self.mass[t]}) s CROSS JOIN (SELECT range AS t FROM range({k})) r",
            "q",
        )

    def marginal(self, keep: tuple[str, ...], but: str = "") -> str:
        """SELECT keep, p from the joint and the tables of the kept clusters."""
        clusters = [t for t in self.spec.clusters if t in keep and t != but]
        source, product, out = f"{self.joint} j", "j.p", []
        for t in clusters:
            on = " AND ".join(f"j.{v} = {t}_.{v}" for v in self.spec.sources(t))
            source += f" JOIN {self.current[t]} {t}_ ON {on}"
            product += f" * {t}_.q"
        for v in keep:
            out.append((f"{v}_.t", v) if v in clusters else (f"j.{v}", v))
        return f"SELECT {', '.join(f'{a} AS {b}' for a, b in out)}, SUM({product}) AS p FROM {source} GROUP BY {', '.join(a for a, _ in out)}"

    def update(self, t: str, trade: TradeOff, form: str | None = None) -> str:
        exponent, terms = update_rule(self.spec, t, trade, form)
        u, q = self.spec.sources(t), self.current[t]
        pt = self.add(f"SELECT q.t, SUM(m.pu * q.q) AS pt FROM {q} q JOIN {self.mass[t]} m USING ({self.cols(u)}) GROUP BY q.t", "pt")
        costs = []
        for term in terms:
            yz = tuple(dict.fromkeys((*term.y, *term.z)))
            w = self.add(self.marginal(tuple(dict.fromkeys((*u, *yz))), t), "w")
            m = self.add(f"SELECT {self.cols(yz, 'w')}, q.t, SUM(w.p * q.q) AS m FROM {w} w JOIN {q} q ON {' AND '.join(f'w.{v} = q.{v}' for v in u)} GROUP BY {self.cols(yz, 'w')}, q.t", "m")
            z = self.cols(term.z) + ", " if term.z else ""
            n = self.add(f"SELECT {z}t, SUM(m) AS n FROM {m} GROUP BY {z}t", "n")
            on_z = " AND ".join([f"m.{v} = n.{v}" for v in term.z] + ["m.t = n.t"])
            on_yz = " AND ".join(f"w.{v} = m.{v}" for v in yz)
            ratio = f"ln(greatest(m.m, {TINY})) - ln(greatest(n.n, {TINY}))"
            costs.append(self.add(f"SELECT {self.cols(u, 'w')}, m.t, -({term.weight}) * SUM(w.p * ({ratio})) AS d FROM {w} w JOIN {m} m ON {on_yz} JOIN {n} n ON {on_z} GROUP BY {self.cols(u, 'w')}, m.t", "d"))
        whole = " UNION ALL ".join(f"SELECT {self.cols(u)}, t, d FROM {c}" for c in costs)
        score = self.add(
            f"SELECT {self.cols(u, 'x')}, x.t, ln(greatest(pt.pt, {TINY})) - ({exponent}) * SUM(x.d) / m.pu AS s FROM ({whole}) x JOIN {pt} pt ON x.t = pt.t "
            f"JOIN {self.mass[t]} m ON {' AND '.join(f'x.{v} = m.{v}' for v in u)} GROUP BY {self.cols(u, 'x')}, x.t, pt.pt, m.pu",
            "s",
        )
        self.last_score = score
        shifted = self.add(f"SELECT {self.cols(u)}, t, exp(s - MAX(s) OVER (PARTITION BY {self.cols(u)})) AS e FROM {score}", "e")
        return self.add(f"SELECT {self.cols(u)}, t, e / SUM(e) OVER (PARTITION BY {self.cols(u)}) AS q FROM {shifted}", "q")

    def sweeps(self, n: int, trade: TradeOff, schedule: str = "async", form: str | None = None) -> SweepScript:
        for _ in range(n):
            if schedule == "async":
                for t in self.spec.clusters:
                    self.current[t] = self.update(t, trade, form)
            else:
                self.current = {t: self.update(t, trade, form) for t in self.spec.clusters}
        return self

    def tables(self) -> str:
        """var, u, t, q of every cluster variable."""
        parts = []
        for t in self.spec.clusters:
            u = "concat_ws('|', " + ", ".join(f"CAST({v} AS VARCHAR)" for v in self.spec.sources(t)) + ")"
            parts.append(f"SELECT '{t}' AS var, {u} AS u, CAST(t AS BIGINT) AS t, round(q, 6) + 0.0 AS q FROM {self.current[t]}")
        return self.ending(" UNION ALL ".join(parts))

    def mutual(self, x: tuple[str, ...], y: tuple[str, ...]) -> str:
        """A scalar expression: the information in nats between two sets, in the current state."""
        keep = tuple(dict.fromkeys((*x, *y)))
        both = self.add(self.marginal(keep), "xy")
        h = lambda vs: f"(SELECT -SUM(p * ln(p)) FROM (SELECT SUM(p) AS p FROM {both} GROUP BY {self.cols(tuple(dict.fromkeys(vs)))}) WHERE p > 0)"
        return f"({h(x)} + {h(y)} - {h(keep)})"

    def objective(self, trade: TradeOff) -> tuple[str, str, str]:
        """Scalar expressions of i_in, i_out and the objective."""
        i_in = " + ".join(self.mutual((t,), self.spec.sources(t)) for t in self.spec.clusters)
        i_out = " + ".join(self.mutual((v,), p) for v, p in self.spec.g_out.parents.items() if p)
        value = f"({i_in}) - {trade.value} * ({i_out})" if trade.kind == "beta" else f"{1 + trade.value} * ({i_in}) - {trade.value} * ({i_out})"
        return i_in, i_out, value

    def ending(self, select: str) -> str:
        return "WITH " + ",\n".join(self.blocks) + "\n" + select


def lcg_sql(level: int, i: str = "i", t: str = "t") -> str:
    return f"((({i} * 7919 + {t} * 104729 + {level * 1299709}) % 10007) / 10006.0::DOUBLE - 0.5)"


class LcgScript(SweepScript):
    """Sweeps from a start of whole numbers: rows proportional to 0.6 + noise."""

    def __init__(self, spec: BottleneckSpec, sizes: dict[str, int], joint_sql: str, level: int = 0):
        self.level = level
        super().__init__(spec, sizes, joint_sql)

    def restart(self, sizes: dict[str, int], level: int) -> LcgScript:
        """New tables over the same joint."""
        self.sizes, self.level = sizes, level
        self.current = {t: self.start(t) for t in self.spec.clusters}
        return self

    def start(self, t: str) -> str:
        k, u = self.sizes[t], self.cols(self.spec.sources(t))
        noise = lcg_sql(self.level + 17 * self.spec.clusters.index(t), "i", "r.t")
        raw = f"SELECT {u}, r.t AS t, 0.6 + {noise} AS e FROM (SELECT {u}, row_number() OVER (ORDER BY {u}) - 1 AS i FROM {self.mass[t]}) s CROSS JOIN (SELECT range AS t FROM range({k})) r"
        return self.add(f"SELECT {u}, t, e / SUM(e) OVER (PARTITION BY {u}) AS q FROM ({raw})", "q")


class AnnealScript(SweepScript):
    """An anneal with a fixed number of sweeps at each weight: doubling, split test and merging as blocks.

    `trees` and `curves` collect SELECTs of what each step finds; clusters are numbered anew after each step.
    """

    def __init__(self, spec: BottleneckSpec, joint_sql: str):
        super().__init__(spec, dict.fromkeys(spec.clusters, 1), joint_sql)
        self.paths = {t: self.add("SELECT 0 AS t, '0' AS node", "path") for t in spec.clusters}
        self.trees = [f"SELECT '{t}' AS var, '0' AS node_id, NULL::VARCHAR AS parent_id, 0 AS level, 0.0::DOUBLE AS beta, 1.0::DOUBLE AS mass, false AS split" for t in spec.clusters]
        self.curves: list[str] = []
        rest = lambda t: tuple(v for v in spec.observed if v not in spec.sources(t))
        self.whole = {t: self.add(f"SELECT {self.mutual(spec.sources(t), rest(t))} AS whole, (SELECT -SUM(pu * ln(pu)) FROM {self.mass[t]}) AS h", "whole") for t in spec.clusters}

    def double(self, t: str, level: int, alpha: float) -> str:
        u, q = self.cols(self.spec.sources(t)), self.current[t]
        ranked = self.add(f"SELECT {u}, t, q, dense_rank() OVER (ORDER BY {u}) - 1 AS i FROM {q}", "r")
        return self.add(f"SELECT {u}, 2 * t AS t, q * (0.5 + {alpha} * {lcg_sql(level)}) AS q FROM {ranked} UNION ALL SELECT {u}, 2 * t + 1, q * (0.5 - {alpha} * {lcg_sql(level)}) FROM {ranked}", "q")

    def keep_split(self, t: str, weight: float, threshold: float, floor: float, most: int) -> None:
        """Pairs that differ become clusters of their own, at most `most` in all; the others are added up."""
        u, q = self.cols(self.spec.sources(t)), self.current[t]
        pt = self.add(f"SELECT t, SUM(pu * q) AS pt FROM {q} JOIN {self.mass[t]} USING ({u}) GROUP BY t", "pt")
        pairs = self.add(f"SELECT {u}, t // 2 AS t, MAX(CASE WHEN t % 2 = 0 THEN q END) AS q0, MAX(CASE WHEN t % 2 = 1 THEN q END) AS q1 FROM {q} GROUP BY {u}, t // 2", "pairs")
        over = self.add(f"SELECT t // 2 AS t, MAX(CASE WHEN t % 2 = 0 THEN pt END) AS pa, MAX(CASE WHEN t % 2 = 1 THEN pt END) AS pb FROM {pt} GROUP BY t // 2", "over")
        gap = f"MAX(CASE WHEN q0 + q1 > {floor} AND pa > {floor} AND pb > {floor} THEN abs(q0 / (q0 + q1) - pa / (pa + pb)) ELSE 0.0 END)"
        gaps = self.add(f"SELECT t, {gap} AS gap FROM {pairs} JOIN {over} USING (t) GROUP BY t", "gaps")
        ruled = f"SELECT t, gap, gap > {threshold} AND row_number() OVER (ORDER BY gap DESC, t) <= {most} - (SELECT count(*) FROM {gaps}) AS apart FROM {gaps}"
        named = self.add(
            f"SELECT r.t, j, apart, row_number() OVER (ORDER BY r.t, j) - 1 AS fresh, node AS parent, CASE WHEN apart THEN node || '.' || j ELSE node END AS node "
            f"FROM ({ruled}) r JOIN {self.paths[t]} USING (t) CROSS JOIN (SELECT range AS j FROM range(2)) WHERE apart OR j = 0",
            "named",
        )
        self.trees.append(f"SELECT '{t}', node, parent, len(node) - len(replace(node, '.', '')), {weight}::DOUBLE, pt, true FROM {named} n JOIN {pt} ON {pt}.t = 2 * n.t + j WHERE apart")
        self.paths[t] = self.add(f"SELECT fresh AS t, node FROM {named}", "path")
        self.current[t] = self.add(f"SELECT {self.cols(self.spec.sources(t), 'q')}, fresh AS t, SUM(q) AS q FROM {q} q JOIN {named} n ON q.t // 2 = n.t AND (NOT apart OR q.t % 2 = j) GROUP BY {self.cols(self.spec.sources(t), 'q')}, fresh", "q")

    def step(self, level: int, trade: TradeOff, sweeps: int, alpha: float = 1.0, threshold: float = 0.05, floor: float = 1e-6, max_k: int = 32) -> AnnealScript:
        for t in self.spec.clusters:
            beside = [u for u in self.spec.clusters if self.spec.sources(u) == self.spec.sources(t)].index(t)
            self.current[t] = self.double(t, level + 31 * beside, alpha)
        self.sweeps(sweeps, trade)
        before = dict(self.paths)
        for t in self.spec.clusters:
            self.keep_split(t, trade.value, threshold, floor, max_k)
        same: dict[tuple[str, ...], list[str]] = {}
        for t in self.spec.clusters:
            same.setdefault(self.spec.sources(t), []).append(t)
        grew = lambda t: f"(SELECT count(*) FROM {self.paths[t]}) > (SELECT count(*) FROM {before[t]})"
        for ts in [(t,) for t in self.spec.clusters] + [tuple(x) for x in same.values() if len(x) > 1]:
            u = self.spec.sources(ts[0])
            rest = tuple(v for v in self.spec.observed if v not in u)
            k = " * ".join(f"(SELECT count(*) FROM {self.paths[t]})" for t in ts)
            self.curves.append(
                f"SELECT {level} AS step, {trade.value}::DOUBLE AS beta, '{','.join(ts)}' AS var, {k} AS k, c / ln(2) AS compression, r / ln(2) AS relevance, c / h AS compression_frac, r / whole AS relevance_frac, {' OR '.join(map(grew, ts))} AS split "
                f"FROM (SELECT {self.mutual(ts, u)} AS c, {self.mutual(ts, rest)} AS r) CROSS JOIN {self.whole[ts[0]]}"
            )
        return self

    def anneal(self, weights: list[float], sweeps: int, **settings) -> AnnealScript:
        for level, value in enumerate(weights):
            self.step(level, TradeOff(self.spec.objective, value), sweeps, **settings)
        return self

    def curve(self) -> str:
        numbers = ", ".join(f"round({c}, 6) + 0.0 AS {c}" for c in ("compression", "relevance", "compression_frac", "relevance_frac"))
        return self.ending(f"SELECT CAST(step AS BIGINT) AS step, beta, var, CAST(k AS BIGINT) AS k, {numbers}, split FROM ({' UNION ALL '.join(self.curves)})")

    def tree(self) -> str:
        return self.ending(f"SELECT var, node_id, parent_id, CAST(level AS BIGINT) AS level, beta, round(mass, 6) AS mass, split FROM ({' UNION ALL '.join(self.trees)})")
