"""DuckDB SQL of the library's queries: an independent reading of the same definitions, for comparing results."""

from __future__ import annotations

from itertools import product

from dpgrid.operators.components import offsets
from dpgrid.operators.grid import GridSpec
from dpgrid.operators.wavelet import Wavelet, get_wavelet
from dpgrid.sources.workloads import WORKLOADS


def num(x: float) -> str:
    return f"CAST({float(x)!r} AS DOUBLE)"


def uniform(key: str, purpose: str, *parts: str) -> str:
    text = ", ".join([f"'{key}'", f"'{purpose}'", *[f"CAST({p} AS VARCHAR)" for p in parts]])
    return f"((CAST(CAST('0x' || substr(md5(concat_ws('|', {text})), 1, 13) AS BIGINT) AS DOUBLE) + 0.5e0) / 4503599627370496e0)"


def laplace(u: str, b: str) -> str:
    return f"(-({b}) * sign({u} - 0.5e0) * ln(1e0 - 2e0 * abs({u} - 0.5e0)))"


class Query:
    """A WITH list under construction."""

    def __init__(self):
        self.parts: list[tuple[str, str]] = []
        self.recursive = False

    def add(self, name: str, body: str) -> Query:
        self.parts.append((name, body))
        return self

    def select(self, body: str) -> str:
        return f"WITH {'RECURSIVE ' if self.recursive else ''}" + ",\n".join(f"{n} AS ({b})" for n, b in self.parts) + "\n" + body

    # Clean side

    def points(self, w: str) -> Query:
        return self.add("pts", WORKLOADS[w].sql("duckdb"))

    def counts(self, w: str, source: str = "pts", name: str = "m", by: str = "") -> Query:
        spec, cols = WORKLOADS[w].spec, WORKLOADS[w].cols
        cell = cell_sql(cols, spec)
        sound = " AND ".join(f"{c} IS NOT NULL AND NOT isnan({c})" for c in cols)
        return self.add(name, f"SELECT {by} cell, count(*) AS cnt FROM (SELECT {by} {cell} AS cell FROM {source} WHERE {sound}) q GROUP BY {by} cell")

    def haar(self, spec: GridSpec, level: int = 1, source: str = "m", name: str = "band", by: str = "", value: str = "cnt") -> Query:
        return self.add(name, f"SELECT {by} wcell, sum(CAST({value} AS DOUBLE)) / {num(2 ** (spec.n * level / 2))} AS w FROM (SELECT {by} {block_sql('cell', spec, level)} AS wcell, {value} FROM {source}) q GROUP BY {by} wcell")

    def runs(self, eps: list[float], reps: int) -> Query:
        rows = ", ".join(f"({i}, {r}, {num(e)})" for i, e in enumerate(eps) for r in range(reps))
        return self.add("runs", f"SELECT * FROM (VALUES {rows}) t(eps_i, rep, eps)")

    # Private side

    def noisy_band(self, spec: GridSpec, key: str, share: float = 1.0, name: str = "nband", band: str = "band") -> Query:
        wide = spec.coarse(1)
        draws = []
        at = unrolled("wcell", wide)
        for inner in product((0, 1), repeat=spec.n):
            cell = rolled([f"(({a}) * 2 + {b})" for a, b in zip(at, inner, strict=True)], spec.g)
            draws.append(laplace(uniform(key, "count", "eps_i", "rep", cell), f"1e0 / (eps * {num(share)})"))
        size = 1
        for k in wide:
            size *= k
        scale = num(2 ** (spec.n / 2))
        return self.add(name, f"SELECT eps_i, rep, wcell, (coalesce(w, 0e0) * {scale} + {' + '.join(draws)}) / {scale} AS w FROM (SELECT d.wcell, b.w FROM (SELECT unnest(range({size})) AS wcell) d LEFT JOIN {band} b USING (wcell)) q CROSS JOIN runs")

    def cut(self, p: float, band: str = "band", name: str = "cut", by: tuple[str, ...] = (), drop: str | None = None) -> Query:
        """``by..., n_pos, k, d``; ``drop`` names a relation with ``by..., r``."""
        key = ", ".join(by)
        comma = key + ", " if by else ""
        part = f"PARTITION BY {key} " if by else ""
        left = "n_pos" if drop is None else "(n_pos - least(greatest(r, 0), n_pos - 1))"
        with_drop = "" if drop is None else (f" JOIN {drop} USING ({key})" if by else f" CROSS JOIN {drop}")
        n = f"SELECT {comma} count(*) AS n_pos FROM {band} WHERE w > 0" + (f" GROUP BY {key}" if by else "")
        k = f"SELECT {comma} n_pos, CAST(least(n_pos, greatest(ceil((1e0 - {num(p)}) * {left} - 1e-9), 0)) AS BIGINT) AS k FROM ({n}) c{with_drop}"
        ranked = f"SELECT {comma} w, row_number() OVER ({part}ORDER BY w DESC) AS rn FROM {band} WHERE w > 0"
        on = " AND ".join([f"r.{c} = k.{c}" for c in by] + ["r.rn = k.k"])
        cols = "".join(f"k.{c}, " for c in by)
        return self.add(name, f"SELECT {cols} k.n_pos, k.k, r.w AS d FROM ({k}) k LEFT JOIN ({ranked}) r ON {on}")

    def keep(self, band: str, cut: str, name: str = "kept", by: tuple[str, ...] = (), test: str = ">=") -> Query:
        join = f"JOIN {cut} USING ({', '.join(by)})" if by else f"CROSS JOIN {cut}"
        return self.add(name, f"SELECT {''.join(c + ', ' for c in by)} wcell, w FROM {band} {join} WHERE w > 0 AND w {test} d")

    def components(self, g: tuple[int, ...], kept: str = "kept", name: str = "lab", by: tuple[str, ...] = (), adjacency: str = "face", periodic: bool = False) -> Query:
        """Labels by a recursive walk; ``name(by..., wcell, cluster)``."""
        self.recursive = True
        at, moves = unrolled("wcell", g), []
        for step in offsets(len(g), adjacency):
            for sign in (1, -1):
                to = [f"(({x}) + {sign * d})" if d else f"({x})" for x, d in zip(at, step, strict=True)]
                if periodic:
                    where, to = "", [f"(({t} + {k}) % {k})" for t, k in zip(to, g, strict=True)]
                else:
                    where = " WHERE " + " AND ".join(f"{t} BETWEEN 0 AND {k - 1}" for t, k in zip(to, g, strict=True))
                moves.append(f"SELECT {''.join(c + ', ' for c in by)}wcell AS x, {rolled(to, g)} AS y FROM {kept}{where}")
        same = " AND ".join([f"m.{c} = b.{c}" for c in by] + ["m.y = b.wcell"])
        plain = "".join(f"{c}, " for c in by)
        self.add(f"{name}_e", f"SELECT {''.join(f'm.{c}, ' for c in by)} x, y FROM ({' UNION ALL '.join(moves)}) m JOIN {kept} b ON {same}")
        step = " AND ".join([f"e.{c} = l.{c}" for c in by] + ["e.x = l.v"])
        self.add(f"{name}_w", f"SELECT {plain} wcell AS v, wcell AS c FROM {kept} UNION SELECT {''.join(f'l.{c}, ' for c in by)} e.y, l.c FROM {name}_w l JOIN {name}_e e ON {step}")
        return self.add(name, f"SELECT {plain} v AS wcell, min(c) AS cluster FROM {name}_w GROUP BY {plain} v")

    def rank_intervals(self, band: str = "band", name: str = "ivals") -> Query:
        self.add(f"{name}_h", f"SELECT w, count(*) AS mult FROM {band} WHERE w > 0 GROUP BY w")
        return self.add(name, f"SELECT CAST(sum(mult) OVER (ORDER BY w DESC) AS BIGINT) AS rank, coalesce(lead(w) OVER (ORDER BY w DESC), 0e0) AS lo, w AS hi FROM {name}_h")

    def sampled_cut(self, key: str, share: float, cut: str = "cut", name: str = "drawn", sensitivity: int = 1) -> Query:
        g = uniform(key, "gumbel", "eps_i", "rep", "rank")
        v = f"ln(hi - lo) + eps * {num(share)} * -abs(rank - k) / {num(2.0 * sensitivity)} - ln(-ln({g}))"
        self.add(f"{name}_v", f"SELECT eps_i, rep, rank, lo, hi, {v} AS v FROM ivals CROSS JOIN (SELECT k FROM {cut}) c CROSS JOIN runs WHERE hi > lo")
        return self.add(name, f"SELECT eps_i, rep, rank AS k_priv, lo + (hi - lo) * {uniform(key, 'within', 'eps_i', 'rep')} AS d FROM {name}_v QUALIFY row_number() OVER (PARTITION BY eps_i, rep ORDER BY v DESC) = 1")

    def nonpositive(self, cells: int, band: str = "band", name: str = "z") -> Query:
        return self.add(name, f"SELECT {cells} - count(*) FILTER (WHERE w > 0) AS n_nonpos FROM {band}")

    def noisy_z(self, key: str, share: float, name: str = "zn") -> Query:
        return self.add(name, f"SELECT eps_i, rep, n_nonpos + {laplace(uniform(key, 'z', 'eps_i', 'rep'), f'1e0 / (eps * {num(share)})')} AS z_noisy FROM z CROSS JOIN runs")

    def filter_axis(self, w: Wavelet, spec: GridSpec, source: str, name: str) -> Query:
        """Average band of a non-Haar filter, one axis after the other, on even grids."""
        wave, g = get_wavelet(w), spec.g
        taps = ", ".join(f"({t + wave.offset}, {num(c)})" for t, c in enumerate(wave.low))
        cur, left = source, [f"i{a}" for a in range(spec.n)]
        self.add(f"{name}_s", f"SELECT {', '.join(f'{e} AS i{a}' for a, e in enumerate(unrolled('cell', g)))}, CAST(cnt AS DOUBLE) AS w FROM {source}")
        cur = f"{name}_s"
        for a, k in enumerate(g):
            diff = f"(((i{a} - s) % {k} + {k}) % {k})"
            rest = ", ".join(x for x in left if x != f"i{a}")
            nxt = f"{name}_{a}"
            self.add(nxt, f"SELECT {rest}, q AS i{a}, sum(v) AS w FROM (SELECT {rest}, {diff} // 2 AS q, w * c AS v FROM {cur} CROSS JOIN (VALUES {taps}) t(s, c) WHERE {diff} % 2 = 0) z GROUP BY {rest}, q")
            cur = nxt
        return self.add(name, f"SELECT CAST({rolled(left, spec.coarse(1))} AS BIGINT) AS wcell, w FROM {cur}")


def cell_sql(cols: list[str], spec: GridSpec) -> str:
    parts = [f"CAST(greatest(least(floor(({c} - {num(lo)}) * {num(g)} / {num(hi - lo)}), {g - 1}), 0) AS BIGINT)" for c, lo, hi, g in zip(cols, spec.lo, spec.hi, spec.g, strict=True)]
    return rolled(parts, spec.g)


def rolled(parts: list[str], g: tuple[int, ...]) -> str:
    made = parts[0]
    for p, k in zip(parts[1:], g[1:], strict=True):
        made = f"({made}) * {k} + {p}"
    return f"({made})"


def unrolled(cell: str, g: tuple[int, ...]) -> list[str]:
    below, made = 1, []
    for k in reversed(g):
        made.append(f"({cell}) // {below} % {k}")
        below *= k
    return made[::-1]


def block_sql(cell: str, spec: GridSpec, level: int = 1) -> str:
    return "CAST(" + rolled([f"(({c}) // {2**level})" for c in unrolled(cell, spec.g)], spec.coarse(level)) + " AS BIGINT)"
