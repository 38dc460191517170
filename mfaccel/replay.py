"""DuckDB SQL that replays the methods at rank 1 and 2, as chains of common table expressions.

The queries' oracles are put together from these parts. Names of tables in a chain: r (ratings u, i, v), and for a point
k the sides u<k> and m<k> with columns id, x0, x1.
"""

from __future__ import annotations

LAM = 0.1

RATINGS = {
    "cust_part": "SELECT CAST(o_custkey AS BIGINT) AS u, CAST(l_partkey AS BIGINT) AS i, avg(l_quantity) / 10 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2",
    "cust_brandtype": "SELECT CAST(o_custkey AS BIGINT) AS u, CAST(regexp_extract(p_brand, '(\\d+)', 1) AS BIGINT) * 10 + code AS i, avg(l_quantity) / 10 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey JOIN (SELECT p_type AS kind, dense_rank() OVER (ORDER BY p_type) - 1 AS code FROM (SELECT DISTINCT p_type FROM part)) ON kind = p_type GROUP BY 1, 2",
    "cust_brandsize": "SELECT CAST(o_custkey AS BIGINT) AS u, CAST(regexp_extract(p_brand, '(\\d+)', 1) AS BIGINT) * 50 + p_size - 1 AS i, avg(l_quantity) / 10 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2",
    "supp_part": "SELECT CAST(l_suppkey AS BIGINT) AS u, CAST(l_partkey AS BIGINT) AS i, avg(l_quantity) / 10 AS v FROM lineitem GROUP BY 1, 2",
    "nation_brand": "SELECT CAST(c_nationkey AS BIGINT) AS u, CAST(regexp_extract(p_brand, '(\\d+)', 1) AS BIGINT) AS i, avg(l_quantity) / 10 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2",
    "event_key": "SELECT user_id AS u, CAST(json_extract_string(props, '$.k') AS BIGINT) AS i, avg(value) AS v FROM events WHERE json_extract_string(props, '$.k') IS NOT NULL GROUP BY 1, 2",
    "event_type": "SELECT user_id AS u, code AS i, CAST(count(*) AS DOUBLE) AS v FROM events JOIN (SELECT event_type AS kind, dense_rank() OVER (ORDER BY event_type) - 1 AS code FROM (SELECT DISTINCT event_type FROM events)) ON kind = event_type GROUP BY 1, 2",
}


def unit(*parts: str) -> str:
    """Uniform in [0, 1) of SQL expressions."""
    return f"(CAST('0x' || substr(md5(concat_ws(':', {', '.join(parts)})), 1, 8) AS BIGINT) / CAST(4294967296 AS DOUBLE))"


def rounded(expr: str) -> str:
    return f"(round({expr}, 6) + 0.0)"


class Chain:
    def __init__(self, view: str = "cust_part", rank: int = 2, lam: float = LAM):
        self.rank, self.lam, self.parts = rank, lam, [("r", RATINGS[view])]

    def add(self, name: str, sql: str) -> "Chain":
        self.parts.append((name, sql))
        return self

    def sql(self, final: str) -> str:
        return "WITH " + ",\n".join(f"{n} AS MATERIALIZED ({s})" for n, s in self.parts) + "\n" + final

    @property
    def ks(self) -> range:
        return range(self.rank)

    def start(self, k: int = 0, seed: int = 42) -> "Chain":
        for name, col, side in ((f"u{k}", "u", "user"), (f"m{k}", "i", "item")):
            xs = ", ".join(f"{unit(f"'{seed}'", f"'{side}'", f'CAST({col} AS VARCHAR)', f"'{j}'")} / sqrt({self.rank}) AS x{j}" for j in self.ks)
            self.add(name, f"SELECT {col} AS id, {xs} FROM (SELECT DISTINCT {col} FROM r)")
        return self

    def half(self, name: str, other: str, side: str) -> "Chain":
        """The exact minimiser of a side."""
        own, key = ("u", "i") if side == "user" else ("i", "u")
        sums = [f"sum(o.x{a} * o.x{b}) + {f'{self.lam} * count(*)' if a == b else '0'} AS a{a}{b}" for a in self.ks for b in range(a, self.rank)]
        sums += [f"sum(v * o.x{a}) AS v{a}" for a in self.ks]
        det = "(a00 * a11 - a01 * a01)"
        xs = "v0 / a00 AS x0" if self.rank == 1 else f"(v0 * a11 - v1 * a01) / {det} AS x0, (v1 * a00 - v0 * a01) / {det} AS x1"
        return self.add(name, f"SELECT id, {xs} FROM (SELECT r.{own} AS id, {', '.join(sums)} FROM r JOIN {other} o ON r.{key} = o.id GROUP BY r.{own})")

    def sweep(self, frm: str, to: str) -> "Chain":
        return self.half(f"u{to}", f"m{frm}", "user").half(f"m{to}", f"u{to}", "item")

    def dot(self, a: str, b: str) -> str:
        return "(" + " + ".join(f"{a}{k} * {b}{k}" for k in self.ks) + ")"

    def cells(self, k: str) -> str:
        return f"r JOIN u{k} u ON r.u = u.id JOIN m{k} m ON r.i = m.id"

    def gradient(self, k: str) -> "Chain":
        """gu<k>, gm<k>: columns id, g0, g1."""
        e = f"({self.dot('u.x', 'm.x')} - v)"
        for name, own, other, col in ((f"gu{k}", "u", "m", "u"), (f"gm{k}", "m", "u", "i")):
            gs = ", ".join(f"sum(2 * ({e} * {other}.x{j} + {self.lam} * {own}.x{j})) AS g{j}" for j in self.ks)
            self.add(name, f"SELECT r.{col} AS id, {gs} FROM {self.cells(k)} GROUP BY r.{col}")
        return self

    def preconditioned(self, k: str) -> "Chain":
        """zu<k>, zm<k>: the point less one sweep from it, columns z0, z1."""
        self.sweep(k, f"b{k}")
        for s in "um":
            self.add(f"z{s}{k}", f"SELECT a.id, {', '.join(f'a.x{j} - b.x{j} AS z{j}' for j in self.ks)} FROM {s}{k} a JOIN {s}b{k} b ON a.id = b.id")
        return self

    def by_gradient(self, k: str) -> "Chain":
        for s in "um":
            self.add(f"z{s}{k}", f"SELECT id, {', '.join(f'g{j} AS z{j}' for j in self.ks)} FROM g{s}{k}")
        return self

    def first_direction(self, k: str) -> "Chain":
        for s in "um":
            self.add(f"p{s}{k}", f"SELECT id, {', '.join(f'-z{j} AS p{j}' for j in self.ks)} FROM z{s}{k}")
        return self

    def quartic(self, k: str, along: str = "p", name: str = "c") -> "Chain":
        """<name><k>: one row c0..c4 along a direction from point k."""
        dot, lam = self.dot, self.lam
        e, b, d = f"({dot('u.x', 'm.x')} - v)", f"({dot('u.x', 'q.p')} + {dot('p.p', 'm.x')})", dot("p.p", "q.p")
        inner = (
            f"SELECT {e} AS e, {b} AS b, {d} AS d, {lam} * ({dot('u.x', 'u.x')} + {dot('m.x', 'm.x')}) AS n0, "
            f"{lam} * 2 * ({dot('u.x', 'p.p')} + {dot('m.x', 'q.p')}) AS n1, {lam} * ({dot('p.p', 'p.p')} + {dot('q.p', 'q.p')}) AS n2 "
            f"FROM {self.cells(k)} JOIN {along}u{k} p ON r.u = p.id JOIN {along}m{k} q ON r.i = q.id"
        )
        return self.add(f"{name}{k}", f"SELECT sum(e * e + n0) AS c0, sum(2 * e * b + n1) AS c1, sum(b * b + 2 * e * d + n2) AS c2, sum(2 * b * d) AS c3, sum(d * d) AS c4 FROM ({inner})")

    def step(self, k: str) -> "Chain":
        """s<k>: the number of reductions and the step of the backtracking search."""
        trial = f"SELECT min(j) AS steps FROM (SELECT c1, c2, c3, c4, CAST(10 AS DOUBLE) * pow(CAST(0.9 AS DOUBLE), j) AS a, j FROM c{k}, range(0, 401) t(j)) WHERE c2 * a + c3 * a * a + c4 * a * a * a <= -0.5 * c1"
        return self.add(f"s{k}", f"SELECT steps, CAST(10 AS DOUBLE) * pow(CAST(0.9 AS DOUBLE), steps) AS alpha FROM ({trial})")

    def move(self, k: str, to: str) -> "Chain":
        for s in "um":
            self.add(f"{s}{to}", f"SELECT a.id, {', '.join(f'a.x{j} + alpha * p{j} AS x{j}' for j in self.ks)} FROM {s}{k} a JOIN p{s}{k} b ON a.id = b.id, s{k}")
        return self

    def weights(self, k: str, to: str) -> "Chain":
        """w<to>: every rule's weight after the move from k to `to`."""
        both = " UNION ALL ".join(
            f"SELECT {', '.join([f'g.g{j} AS g{j}, h.g{j} AS h{j}, z.z{j} AS z{j}, y.z{j} AS y{j}, p.p{j} AS p{j}' for j in self.ks])} FROM g{s}{to} g JOIN g{s}{k} h ON g.id = h.id JOIN z{s}{to} z ON z.id = g.id JOIN z{s}{k} y ON y.id = g.id JOIN p{s}{k} p ON p.id = g.id"
            for s in "um"
        )
        dot = self.dot
        names = {"gg": "g g", "gh": "g h", "hh": "h h", "zg": "z g", "zh": "z h", "yh": "y h", "zz": "z z", "zy": "z y", "yy": "y y", "pg": "p g", "ph": "p h"}
        sums = ", ".join(f"sum({dot(*v.split())}) AS {n}" for n, v in names.items())
        return self.add(f"w{to}", f"SELECT *, (gg - gh) / hh AS pr, (zg - zh) / yh AS pr_pre, (zz - zy) / yy AS pr_tilde, gg / hh AS fr, zg / yh AS fr_pre, (gg - gh) / (pg - ph) AS hs, (zg - zh) / (pg - ph) AS hs_pre FROM (SELECT {sums} FROM ({both}))")

    def direction(self, k: str, to: str, rule: str = "pr_pre") -> "Chain":
        """p<to>: the new direction, or the preconditioned gradient alone if that one does not descend."""
        weight = rule if rule != "zero" else "0"
        for s in "um":
            self.add(f"d{s}{to}", f"SELECT z.id, {', '.join(f'-z{j} + {weight} * p{j} AS p{j}' for j in self.ks)} FROM z{s}{to} z JOIN p{s}{k} p ON z.id = p.id, w{to}")
        self.quartic(to, "d", "q")
        for s in "um":
            self.add(f"p{s}{to}", f"SELECT z.id, {', '.join(f'CASE WHEN c1 >= 0 THEN -z{j} ELSE p{j} END AS p{j}' for j in self.ks)} FROM z{s}{to} z JOIN d{s}{to} p ON z.id = p.id, q{to}")
        return self

    def accelerate(self, iterations: int, rule: str = "pr_pre", by: str = "als") -> "Chain":
        look = self.preconditioned if by == "als" else self.by_gradient
        self.start(0).gradient("0")
        look("0")
        self.first_direction("0").quartic("0")
        for k in range(iterations):
            a, b = str(k), str(k + 1)
            self.step(a).move(a, b).gradient(b)
            look(b)
            self.weights(a, b).direction(a, b, rule).quartic(b)
        return self

    def loss(self, k: str) -> str:
        e = f"({self.dot('u.x', 'm.x')} - v)"
        return f"SELECT sum({e} * {e}) AS sse, {self.lam} * sum({self.dot('u.x', 'u.x')}) AS reg_u, {self.lam} * sum({self.dot('m.x', 'm.x')}) AS reg_m FROM {self.cells(k)}"

    def norm(self, k: str) -> str:
        g = self.dot("g", "g")
        return f"SELECT sqrt(sum(s)) / ({self.rank} * count(*)) AS gnorm FROM (SELECT {g} AS s FROM gu{k} UNION ALL SELECT {g} AS s FROM gm{k})"

    def both(self, k: str) -> str:
        xs = ", ".join(f"{rounded(f'x{j}')} AS x{j}" for j in self.ks)
        return f"SELECT 'user' AS side, id, {xs} FROM u{k} UNION ALL SELECT 'item' AS side, id, {xs} FROM m{k}"
