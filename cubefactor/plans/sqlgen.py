"""SQL text of whole solver runs, for engines that materialise common table expressions.

Spark inlines such expressions, so the solvers never run this text; it is the independent reference that the
results are compared with. Sizes of groups up to three columns are solved in closed form.
"""

from __future__ import annotations

from ..operators.tensor import portable_sql


def _solution(width: int, weight: str) -> list[str]:
    """Closed forms of the row solve; g and b are the sums, `weight` the penalty."""
    g = lambda a, b: f"(g{min(a, b)}{max(a, b)}" + (f" + {weight})" if a == b else ")")
    if width == 1:
        return [f"b0 / {g(0, 0)}"]
    if width == 2:
        det = f"({g(0, 0)} * {g(1, 1)} - {g(0, 1)} * {g(0, 1)})"
        return [f"(b0 * {g(1, 1)} - b1 * {g(0, 1)}) / {det}", f"(b1 * {g(0, 0)} - b0 * {g(0, 1)}) / {det}"]
    if width == 3:
        cell = [[g(a, b) for b in range(3)] for a in range(3)]
        det = lambda m: f"({m[0][0]} * ({m[1][1]} * {m[2][2]} - {m[1][2]} * {m[2][1]}) - {m[0][1]} * ({m[1][0]} * {m[2][2]} - {m[1][2]} * {m[2][0]}) + {m[0][2]} * ({m[1][0]} * {m[2][1]} - {m[1][1]} * {m[2][0]}))"
        swapped = lambda k: [[f"b{a}" if b == k else cell[a][b] for b in range(3)] for a in range(3)]
        return [f"{det(swapped(k))} / {det(cell)}" for k in range(3)]
    raise ValueError("closed forms go up to three columns")


class Chain:
    """Builds the steps one after another; `tables` names the newest slices and residual."""

    def __init__(self, cells_sql: str, n_modes: int, rank: int, *, lam: float, reg: str = "weighted", seed: int = 42, init: str = "zero_first") -> None:
        self.n_modes, self.rank, self.lam, self.reg = n_modes, rank, lam, reg
        self.steps: list[tuple[str, str]] = []
        self.number = 0
        modes = ", ".join(f"i{n}" for n in range(1, n_modes + 1))
        self.modes = modes
        self._add("cells", cells_sql)
        self.residual = self._add("r0", f"SELECT {modes}, x, x AS r FROM cells")
        self.value: dict[tuple[int, int], tuple[str, str]] = {}  # (mode, column) -> table and its column
        for n in range(1, n_modes + 1):
            values = ", ".join(("CAST(0 AS DOUBLE)" if init == "zero_first" and n == 1 else portable_sql("idx", n, k, seed)) + f" AS v{k}" for k in range(rank))
            name = self._add(f"start{n}", f"SELECT idx, {values} FROM (SELECT DISTINCT i{n} AS idx FROM cells)")
            for k in range(rank):
                self.value[n, k] = (name, f"v{k}")

    def _add(self, name: str, sql: str) -> str:
        self.steps.append((name, sql))
        return name

    def _next(self, stem: str) -> str:
        self.number += 1
        return f"{stem}_{self.number}"

    def _joined(self, source: str, group: list[int], modes: list[int]) -> tuple[str, dict]:
        """FROM clause that brings the group's values of some modes to the cells, and how to name them."""
        text, names, seen = f"{source} AS c", {}, {}
        for n in modes:
            for k in group:
                table, column = self.value[n, k]
                if (n, table) not in seen:
                    seen[n, table] = f"t{len(seen)}"
                    text += f" JOIN {table} AS {seen[n, table]} ON c.i{n} = {seen[n, table]}.idx"
                names[n, k] = f"{seen[n, table]}.{column}"
        return text, names

    def _total(self, group: list[int], names: dict) -> str:
        return " + ".join("(" + " * ".join(names[n, k] for n in range(1, self.n_modes + 1)) + ")" for k in group)

    def group(self, group: list[int], inner: int = 1) -> None:
        """All steps of one group of columns."""
        every = list(range(1, self.n_modes + 1))
        cells = ", ".join(f"c.i{n}" for n in every)
        source, names = self._joined(self.residual, group, every)
        work = self._add(self._next("back"), f"SELECT {cells}, c.x, c.r + {self._total(group, names)} AS r FROM {source}")
        for _ in range(inner):
            for n in every:
                self.solve(work, n, group)
        source, names = self._joined(work, group, every)
        self.residual = self._add(self._next("left"), f"SELECT {cells}, c.x, c.r - ({self._total(group, names)}) AS r FROM {source}")

    def equations(self, work: str, mode: int, group: list[int]) -> str:
        others = [n for n in range(1, self.n_modes + 1) if n != mode]
        source, names = self._joined(work, group, others)
        p = [" * ".join(names[n, k] for n in others) for k in group]
        width = len(group)
        sums = [f"sum({p[a]} * {p[b]}) AS g{a}{b}" for a in range(width) for b in range(a, width)] + [f"sum(c.r * {p[a]}) AS b{a}" for a in range(width)]
        return self._add(self._next("sums"), f"SELECT c.i{mode} AS idx, {', '.join(sums)}, CAST(count(*) AS DOUBLE) AS n FROM {source} GROUP BY c.i{mode}")

    def solve(self, work: str, mode: int, group: list[int]) -> None:
        sums = self.equations(work, mode, group)
        weight = f"CAST({self.lam} AS DOUBLE)" + (" * n" if self.reg == "weighted" else "")
        solved = _solution(len(group), weight)
        name = self._add(self._next("rows"), f"SELECT idx, {', '.join(f'{s} AS w{a}' for a, s in enumerate(solved))} FROM {sums}")
        for a, k in enumerate(group):
            self.value[mode, k] = (name, f"w{a}")

    def outer(self, width: int, inner: int = 1) -> None:
        for a in range(0, self.rank, width):
            self.group(list(range(self.rank))[a : a + width], inner)

    def factors(self, digits: int) -> str:
        """(mode, idx, component, value)."""
        parts = [f"SELECT {n} AS mode, idx, {k} AS component, round({self.value[n, k][1]} + 0.0, {digits}) + 0.0 AS value FROM {self.value[n, k][0]}" for n in range(1, self.n_modes + 1) for k in range(self.rank)]
        return " UNION ALL ".join(parts)

    def sql(self, final: str) -> str:
        return "WITH " + ", ".join(f"{name} AS MATERIALIZED ({text})" for name, text in self.steps) + " " + final
