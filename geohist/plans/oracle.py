"""DuckDB SQL for the registered queries, written apart from the engine: dense cells, brute force, unrolled levels."""

from __future__ import annotations

SIDE = 64
#: The published test key, and the public domains (x_lo, x_hi, y_lo, y_hi) of the point sets; stated here, not imported.
TEST_SECRET = "public-test-key"
DOMAINS = {
    "p1": (1704067200e6, 1706659200e6, 0.0, 500.0),
    "p2": (788918400e6, 1009843200e6, 0.0, 106000.0),
    "p3": (0.0, 52.0, 0.0, 106000.0),
    "p4": (-1.0, 1.0, -1.0, 1.0),
    "p5": (0.0, 14.0, 0.0, 1.0),
    "p6": (788918400e6, 999302400e6, 0.0, 500000.0),
    "p7": (0.0, 25.0, -1000.0, 10000.0),
}


def levels(eps: float, h: int, allocation: str = "geo", growth: float = 2.0) -> list[float]:
    """Budgets of heights 0 to h, from the ratio between neighbouring levels: each is `growth` to the third part of the one above."""
    ratio, out = (growth ** (1 / 3) if allocation == "geo" else 1.0), [1.0]
    while len(out) <= h:
        out.insert(0, out[0] * ratio)
    return [eps * x / sum(out) for x in out]


def remaining(parts: list[float], h: int) -> float:
    """What is left for a path that stops at height h: the budgets of the levels below it."""
    return sum(p for i, p in enumerate(parts) if i < h)


def u(*parts: str, secret: str = TEST_SECRET) -> str:
    key = " || '/' || ".join([f"'{secret}'", *(f"cast({p} AS VARCHAR)" for p in parts)])
    return f"((cast('0x' || substr(sha256({key}), 1, 12) AS BIGINT) + 0.5) / 281474976710656.0)"


def q(text: str) -> str:
    return f"'{text}'"


def lap(value: str, scale: str, *parts: str) -> str:
    x = f"({u(*parts)} - 0.5)"
    return f"({value} - sign({x}) * ln(1 - 2 * abs({x})) * ({scale}))"


def gum(*parts: str) -> str:
    return f"(-ln(-ln({u(*parts)})))"


_XY = {
    "p1": ("events", "epoch_us(ts)", "value"),
    "p2": ("lineitem", "epoch_us(l_shipdate)", "l_extendedprice"),
    "p3": ("lineitem", "l_quantity", "l_extendedprice"),
    "p4": ("embeddings", "embedding[1]", "embedding[2]"),
    "p5": ("documents", "ln(n_chars)", "(doc_id % 200) / 200"),
    "p6": ("orders", "epoch_us(o_orderdate)", "o_totalprice"),
    "p7": ("customer JOIN nation ON c_nationkey = n_nationkey", "c_nationkey", "c_acctbal"),
}


def points(s: str) -> str:
    source, x, y = _XY[s]
    return f"SELECT cast({x} AS DOUBLE) AS px, cast({y} AS DOUBLE) AS py FROM {source}"


def index(v: str, lo: float, hi: float, n: int) -> str:
    return f"least({n - 1}, cast(floor((greatest({lo!r}, least({hi!r}, {v})) - {lo!r}) * {n} / {hi - lo!r}) AS INTEGER))"


def matrix(s: str, n: int = SIDE) -> str:
    a, b, c, d = DOMAINS[s]
    return f"SELECT {index('px', a, b, n)} AS cx, {index('py', c, d, n)} AS cy, count(*) AS cnt FROM ({points(s)}) p GROUP BY 1, 2"


def dense(s: str, n: int = SIDE) -> str:
    return f"SELECT cast(gx.v AS INTEGER) AS cx, cast(gy.v AS INTEGER) AS cy, coalesce(m.cnt, 0) AS cnt FROM range({n}) gx(v) CROSS JOIN range({n}) gy(v) LEFT JOIN ({matrix(s, n)}) m ON m.cx = gx.v AND m.cy = gy.v"


class Tree:
    """CTEs l{h} (node, x0, x1, y0, y1, cnt, split_at) of every level of a tree, built by brute force from dense cells."""

    def __init__(self, s: str, height: int, method: str, eps: float, tree: str, n: int = SIDE, rounds: int = 3):
        self.height, self.tree, self.cte = height, tree, [f"d AS MATERIALIZED ({dense(s, n)})", f"b{height} AS (SELECT cast(1 AS BIGINT) AS node, 0 AS x0, {n} AS x1, 0 AS y0, {n} AS y1)"]
        for h in range(height, 0, -1):
            self._level(h, method, eps, rounds)
        self.cte.append("l0 AS (SELECT b.*, (SELECT coalesce(sum(cnt), 0) FROM d WHERE cx >= x0 AND cx < x1 AND cy >= y0 AND cy < y1) AS cnt, cast(NULL AS INTEGER) AS split_at FROM b0 b)")

    def _level(self, h: int, method: str, eps: float, rounds: int) -> None:
        a, lo, hi, v = ("cx", "x0", "x1", "(y1 - y0)") if h % 2 == 0 else ("cy", "y0", "y1", "(x1 - x0)")
        w, t, add = f"_{h}", q(self.tree), self.cte.append
        add(f"c{w} AS MATERIALIZED (SELECT node, {hi} - {lo} AS u, {v} AS v, {a} - {lo} + 1 AS pos, cnt FROM b{h} JOIN d ON cx >= x0 AND cx < x1 AND cy >= y0 AND cy < y1)")
        add(f"k{w} AS (SELECT node, {hi} - {lo} AS u, {v} AS v, cast(unnest(range(1, {hi} - {lo})) AS INTEGER) AS k FROM b{h})")
        if method == "em_median":
            add(f"s{w} AS (SELECT k.node, k, abs(2 * sum(CASE WHEN pos <= k THEN cnt ELSE 0 END) - sum(cnt)) AS gap FROM k{w} k JOIN c{w} c ON c.node = k.node GROUP BY 1, 2)")
            add(f"z{w} AS (SELECT node, arg_min(k, gap * {eps!r} / 2 - {gum(t, q('rank'), 'node', 'k')}) AS k FROM s{w} GROUP BY 1)")
        elif method == "midpoint":
            add(f"z{w} AS (SELECT node, 1 + ({hi} - {lo} - 1) // 2 AS k FROM b{h} WHERE {hi} - {lo} > 1)")
        else:
            add(f"m{w} AS (SELECT k.node, k, any_value(k.u) AS u, sum(CASE WHEN pos <= k THEN cnt ELSE 0 END) / any_value(k.k * k.v) AS lowm, sum(CASE WHEN pos > k THEN cnt ELSE 0 END) / any_value((k.u - k.k) * k.v) AS highm FROM k{w} k JOIN c{w} c ON c.node = k.node GROUP BY 1, 2)")
            add(f"o{w} AS MATERIALIZED (SELECT m.node, k, any_value(m.u) AS u, sum(abs(cnt - CASE WHEN pos <= k THEN lowm ELSE highm END)) AS o FROM m{w} m JOIN c{w} c ON c.node = m.node GROUP BY 1, 2)")
            if method == "exact":
                add(f"z{w} AS (SELECT node, k FROM o{w} QUALIFY row_number() OVER (PARTITION BY node ORDER BY round(o, 7), k) = 1)")
            elif method == "exhaustive":
                add(f"z{w} AS (SELECT node, arg_min(k, {lap('o', f'2.0 * (u - 1) / {eps!r}', t, q('split'), 'node', 'k')}) AS k FROM o{w} GROUP BY 1)")
            elif method == "exponential_unevenness":
                add(f"z{w} AS (SELECT node, arg_min(k, o * {eps!r} / 4 - {gum(t, q('rank'), 'node', 'k')}) AS k FROM o{w} GROUP BY 1)")
            else:
                add(f"f{w} AS MATERIALIZED (SELECT node, k, u, {lap('o', f'{2.0 * (2 * rounds + 1) / eps!r}', t, q('split'), 'node', 'k')} AS y FROM o{w})")
                add(f"s{w}_0 AS (SELECT node, 1 AS l, {hi} - {lo} AS r, 1 + ({hi} - {lo} - 1) // 2 AS k FROM b{h} WHERE {hi} - {lo} > 1)")
                for i in range(rounds):
                    add(
                        f"s{w}_{i + 1} AS (SELECT node, CASE WHEN g = 0 THEN a WHEN g < 0 THEN l ELSE k END AS l, CASE WHEN g = 0 THEN b WHEN g < 0 THEN k ELSE r END AS r, CASE WHEN g = 0 THEN k WHEN g < 0 THEN a ELSE b END AS k FROM ("
                        f"SELECT s.*, CASE WHEN fk.y <= fa.y AND fk.y <= fb.y THEN 0 WHEN fa.y <= fb.y THEN -1 ELSE 1 END AS g FROM (SELECT node, l, r, k, l + (k - l) // 2 AS a, k + (r - k) // 2 AS b FROM s{w}_{i}) s "
                        f"JOIN f{w} fa ON fa.node = s.node AND fa.k = s.a JOIN f{w} fk ON fk.node = s.node AND fk.k = s.k JOIN f{w} fb ON fb.node = s.node AND fb.k = s.b))"
                    )
                add(f"z{w} AS (SELECT node, k FROM s{w}_{rounds})")
        add(f"n{w} AS (SELECT node, sum(cnt) AS cnt FROM c{w} GROUP BY 1)")
        add(f"l{h} AS MATERIALIZED (SELECT b.*, n.cnt, cast({lo} + z.k AS INTEGER) AS split_at FROM b{h} b JOIN n{w} n ON n.node = b.node LEFT JOIN z{w} z ON z.node = b.node)")
        left = "x0, split_at AS x1, y0, y1" if h % 2 == 0 else "x0, x1, y0, split_at AS y1"
        right = "split_at AS x0, x1, y0, y1" if h % 2 == 0 else "x0, x1, split_at AS y0, y1"
        add(f"b{h - 1} AS (SELECT 2 * node AS node, {left} FROM l{h} WHERE split_at IS NOT NULL UNION ALL SELECT 2 * node + 1, {right} FROM l{h} WHERE split_at IS NOT NULL)")

    def nodes(self) -> str:
        every = " UNION ALL ".join(f"SELECT node, {h} AS height, x0, x1, y0, y1, split_at, cnt FROM l{h}" for h in range(self.height, -1, -1))
        self.cte.append(f"nodes AS MATERIALIZED ({every})")
        return "nodes"

    def sql(self, final: str) -> str:
        return "WITH " + ",\n".join(self.cte) + "\n" + final

    def node_sql(self) -> str:
        self.nodes()
        return self.sql("SELECT node AS node_id, cast(height AS INTEGER) AS height, cast(x0 AS INTEGER) AS x0, cast(x1 AS INTEGER) AS x1, cast(y0 AS INTEGER) AS y0, cast(y1 AS INTEGER) AS y1, coalesce(split_at, -1) AS split_at, cast(cnt AS BIGINT) AS cnt FROM nodes")

    def pruned(self, eps_data: float, min_count: float | None, min_cells: int | None, allocation: str = "geo") -> None:
        """CTE `leaf` (node, height, x0, x1, y0, y1, cnt, ncount) of the pruned release."""
        self.nodes()
        parts, t = levels(eps_data, self.height, allocation), q(self.tree)
        for h in range(self.height, -1, -1):
            above = f"SELECT n.* FROM nodes n WHERE height = {h}" if h == self.height else f"SELECT n.* FROM nodes n JOIN a{h + 1} p ON p.node = n.node // 2 AND NOT p.stops WHERE n.height = {h}"
            stop = " OR ".join(["split_at IS NULL", *([f"draw <= {min_count!r}"] if min_count is not None else []), *([f"(x1 - x0) * (y1 - y0) < {min_cells}"] if min_cells is not None else [])])
            self.cte.append(f"a{h} AS MATERIALIZED (SELECT *, ({stop}) AS stops FROM (SELECT *, {lap('cnt', repr(1 / parts[h]), t, q('decide'), 'node')} AS draw FROM ({above})))")
        final = [f"SELECT node, height, x0, x1, y0, y1, cnt, {'draw' if h == 0 else lap('cnt', repr(1 / remaining(parts, h)), t, q('final'), 'node')} AS ncount FROM a{h} WHERE stops" for h in range(self.height, -1, -1)]
        self.cte.append("leaf AS MATERIALIZED (" + " UNION ALL ".join(final) + ")")

    LEAF = "SELECT node AS leaf_id, cast(x0 AS INTEGER) AS x0, cast(x1 AS INTEGER) AS x1, cast(y0 AS INTEGER) AS y0, cast(y1 AS INTEGER) AS y1, cast((x1 - x0) * (y1 - y0) AS BIGINT) AS cells, round(ncount, 6) AS ncount FROM leaf"

    def all_nodes(self, eps_data: float, allocation: str = "geo") -> None:
        """CTE `noisy`: nodes with ncount and the variance of their noise."""
        self.nodes()
        parts = levels(eps_data, self.height, allocation)
        scale = "CASE height " + " ".join(f"WHEN {h} THEN {1 / e!r}" for h, e in enumerate(parts)) + " END"
        self.cte.append(f"noisy AS MATERIALIZED (SELECT *, {lap('cnt', scale, q(self.tree), q('decide'), 'node')} AS ncount, 2 * ({scale}) * ({scale}) AS v FROM nodes)")

    def smooth(self) -> None:
        """CTE `fine` (node, x): least squares over `noisy`, unrolled up and down."""
        self.cte.append("up0 AS MATERIALIZED (SELECT node, ncount AS z, v AS s, NULL::DOUBLE AS zc, NULL::DOUBLE AS sc FROM noisy WHERE height = 0)")
        for h in range(1, self.height + 1):
            self.cte.append(
                f"up{h} AS MATERIALIZED (SELECT n.node, CASE WHEN k.s IS NULL THEN ncount ELSE (ncount / v + k.z / k.s) / (1 / v + 1 / k.s) END AS z, CASE WHEN k.s IS NULL THEN v ELSE 1 / (1 / v + 1 / k.s) END AS s, k.z AS zc, k.s AS sc "
                f"FROM noisy n LEFT JOIN (SELECT node // 2 AS p, sum(z) AS z, sum(s) AS s FROM up{h - 1} GROUP BY 1) k ON k.p = n.node WHERE n.height = {h})"
            )
        self.cte.append(f"dn{self.height} AS (SELECT node, z AS x, zc, sc FROM up{self.height})")
        for h in range(self.height - 1, -1, -1):
            self.cte.append(f"dn{h} AS MATERIALIZED (SELECT c.node, c.z + (p.x - p.zc) * c.s / p.sc AS x, c.zc, c.sc FROM up{h} c JOIN dn{h + 1} p ON p.node = c.node // 2)")
        self.cte.append("fine AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT node, x FROM dn{h}" for h in range(self.height, -1, -1)) + ")")


def rects(workload: str, n: int | None, width: str, height: str, side: int = SIDE, seed: str = "q", rows: str | None = None) -> str:
    """n rectangles, or one for each of `rows` (i)."""
    c = lambda f: u(q("query"), q(workload), "i", q(f), secret=seed)
    w, h = (x.replace("$", c(f)) for x, f in ((width, "w"), (height, "h")))
    return (
        f"SELECT {q(workload)} AS workload, i AS qid, cast(greatest(0, mx - w // 2) AS INTEGER) AS x0, cast(least({side}, mx - w // 2 + w) AS INTEGER) AS x1, cast(greatest(0, my - h // 2) AS INTEGER) AS y0, cast(least({side}, my - h // 2 + h) AS INTEGER) AS y1 "
        f"FROM (SELECT i, cast(floor({c('x')} * {side}) AS INTEGER) AS mx, cast(floor({c('y')} * {side}) AS INTEGER) AS my, {w} AS w, {h} AS h FROM {rows or f'range({n}) r(i)'})"
    )


def square_rects(share: float, n: int, side: int = SIDE) -> str:
    s = str(max(1, round((share * side * side) ** 0.5)))
    return rects(f"square_{round(share * 100)}", n, s, s, side)


def random_rects(n: int | None, side: int = SIDE, rows: str | None = None) -> str:
    f = f"(1 + cast(floor($ * {side}) AS INTEGER))"
    return rects("random", n, f, f, side, rows=rows)


def exact_answers(queries: str, s: str, n: int = SIDE) -> str:
    return f"SELECT workload, qid, cast(coalesce(sum(cnt), 0) AS BIGINT) AS exact FROM ({queries}) r LEFT JOIN ({matrix(s, n)}) m ON cx >= x0 AND cx < x1 AND cy >= y0 AND cy < y1 GROUP BY 1, 2"


def private_answers(queries: str, leaves: str = "leaf", value: str = "ncount") -> str:
    share = "(least(r.x1, l.x1) - greatest(r.x0, l.x0)) * (least(r.y1, l.y1) - greatest(r.y0, l.y0)) / ((l.x1 - l.x0) * (l.y1 - l.y0))"
    return f"SELECT workload, qid, coalesce(sum({value} * {share}), 0) AS private FROM ({queries}) r LEFT JOIN {leaves} l ON r.x0 < l.x1 AND l.x0 < r.x1 AND r.y0 < l.y1 AND l.y0 < r.y1 GROUP BY 1, 2"


def blocks(m: int, n: int = SIDE) -> tuple[str, str]:
    """First cell of block g and the one after its last, as templates with $ for g."""
    return f"cast(ceil($ * {n} / {m}) AS INTEGER)", f"cast(ceil(($ + 1) * {n} / {m}) AS INTEGER)"


def grid_blocks(s: str, m: int, n: int = SIDE) -> str:
    """(gx, gy, cnt) of all m by m blocks."""
    return f"SELECT cx * {m} // {n} AS gx, cy * {m} // {n} AS gy, sum(cnt) AS cnt FROM ({dense(s, n)}) GROUP BY 1, 2"


def block_rows(frame: str, m: int, leaf: str, n: int = SIDE) -> str:
    a, b = blocks(m, n)
    x0, x1, y0, y1 = a.replace("$", "gx"), b.replace("$", "gx"), a.replace("$", "gy"), b.replace("$", "gy")
    return f"SELECT cast({leaf} AS BIGINT) AS leaf_id, {x0} AS x0, {x1} AS x1, {y0} AS y0, {y1} AS y1, cast(({x1} - {x0}) * ({y1} - {y0}) AS BIGINT) AS cells, round(ncount, 6) AS ncount FROM ({frame})"
