"""The methods as DuckDB statements: chains of common table expressions, one per tree level and round."""

from __future__ import annotations

from collections.abc import Sequence

from strata.sources.fixtures import CENTRES, INITIAL, SEED, UNIT


def _noise(key: str, axis: str) -> str:
    h = f"md5(concat('{SEED}:', {key}, ':{axis}'))"
    return "(" + " + ".join(f"('0x' || substr({h}, {4 * k + 1}, 4))::BIGINT" for k in range(8)) + " - 262140)"


def _gauss(key: str, source: str) -> str:
    at = lambda a: "CASE " + " ".join(f"WHEN {key} % 4 = {k} THEN {c[a] * UNIT}" for k, c in enumerate(CENTRES)) + " END"
    return f"SELECT {key}::BIGINT point_id, ({at(0)} + 2 * {_noise(key, 'x')})::BIGINT c0, ({at(1)} + 2 * {_noise(key, 'y')})::BIGINT c1, ({key} % 4)::INT truth FROM {source}"


_LINE = "l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate"
POINTS = {
    "gauss3k": _gauss("event_id", "events WHERE event_id < 3000"),
    "gauss_events": _gauss("event_id", "events"),
    "gauss15k": _gauss("o_orderkey", "orders"),
    "orders2d": "SELECT o_orderkey point_id, round(o_totalprice * 100)::BIGINT c0, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::BIGINT c1 FROM orders",
    "lineitem2d": f"SELECT row_number() OVER (ORDER BY {_LINE})::BIGINT point_id, l_quantity::BIGINT c0, round(l_extendedprice * 100)::BIGINT c1 FROM lineitem",
    "events2d": "SELECT event_id point_id, round(value * 100)::BIGINT c0, (hour(ts) * 3600 + minute(ts) * 60 + second(ts))::BIGINT c1 FROM events",
    "customer2d": "SELECT c_custkey point_id, round(c_acctbal * 100)::BIGINT c0, c_nationkey::BIGINT c1 FROM customer",
    "supplier1d": "SELECT s_suppkey point_id, round(s_acctbal * 100)::BIGINT c0 FROM supplier",
    "part2d": "SELECT p_partkey point_id, p_size::BIGINT c0, round(p_retailprice * 100)::BIGINT c1 FROM part",
    "docs2d": "SELECT doc_id point_id, n_chars c0, len(string_split(text, ' '))::BIGINT c1 FROM documents",
    "pages2d": "SELECT page_id point_id, length(html)::BIGINT c0, length(url)::BIGINT c1 FROM pages",
    "nation1d": "SELECT n_nationkey::BIGINT point_id, n_regionkey::BIGINT c0 FROM nation",
    "region1d": "SELECT r_regionkey::BIGINT point_id, r_regionkey::BIGINT c0 FROM region",
    "line8": "SELECT i::BIGINT point_id, (i + 1)::BIGINT c0 FROM range(8) t(i)",
    "embed8": "SELECT vec_id point_id, " + ", ".join(f"floor(embedding[{k + 1}]::DOUBLE * 1000000)::BIGINT c{k}" for k in range(8)) + " FROM embeddings",
}
DIMENSIONS = {"supplier1d": 1, "nation1d": 1, "region1d": 1, "line8": 1, "embed8": 8}


def dims(fixture: str) -> int:
    return DIMENSIONS.get(fixture, 2)


def cols(d: int, prefix: str = "c") -> str:
    return ", ".join(f"{prefix}{k}" for k in range(d))


class Chain:
    """Named steps of one statement over a point set."""

    def __init__(self, fixture: str, where: str = "true"):
        self.d = dims(fixture)
        self.steps = [f"p AS MATERIALIZED (SELECT * FROM ({POINTS[fixture]}) WHERE {where})"]

    def add(self, name: str, sql: str) -> "Chain":
        self.steps.append(f"{name} AS MATERIALIZED ({sql})")
        return self

    def select(self, sql: str) -> str:
        return "WITH " + ",\n".join(self.steps) + "\n" + sql

    def tree(self, depth: int, widest: bool = False) -> "Chain":
        c = cols(self.d)
        self.add("t0", f"SELECT point_id, {c}, 1::BIGINT region_id FROM p")
        for level in range(depth):
            by, source = f"c{level % self.d}", f"t{level}"
            if widest:  # the first of the widest axes
                extents = ", ".join(f"max(c{k}) OVER w - min(c{k}) OVER w e{k}" for k in range(self.d))
                source = f"(SELECT *, {extents} FROM t{level} WINDOW w AS (PARTITION BY region_id))"
                by = "CASE " + " ".join(f"WHEN e{k} >= greatest({cols(self.d, 'e')}) THEN c{k}" for k in range(self.d)) + " END"
            ranked = f"SELECT *, row_number() OVER (PARTITION BY region_id ORDER BY {by}, point_id) rn, count(*) OVER (PARTITION BY region_id) n FROM {source}"
            self.add(f"t{level + 1}", f"SELECT point_id, {c}, region_id * 2 + CASE WHEN rn > (n + 1) // 2 THEN 1 ELSE 0 END region_id FROM ({ranked})")
        return self.add("regions", f"SELECT * FROM t{depth}")

    def labels(self, how: str = "axis", m: int | str | None = None, ragged: str = "keep", seed: int = 0) -> "Chain":
        order = "c0, point_id" if how == "axis" else f"md5(concat('{seed}:', point_id)), point_id"
        ranked = f"SELECT *, row_number() OVER (PARTITION BY region_id ORDER BY {order}) rn, count(*) OVER (PARTITION BY region_id) n FROM regions"
        label = f"((rn - 1) * {m}) // n + 1" if ragged == "proportional" else "rn"
        return self.add("lab", f"SELECT point_id, {cols(self.d)}, region_id, ({label})::BIGINT AS label FROM ({ranked})" + (f" WHERE rn <= {m}" if ragged == "drop" else ""))

    def dealt(self, m: int | str, seed: int = 0) -> "Chain":
        """The random partition without a tree."""
        h = f"md5(concat('{seed}:', point_id))"
        return self.add("lab", f"SELECT point_id, {cols(self.d)}, ((row_number() OVER (ORDER BY substr({h}, 1, 3), {h}, point_id) - 1) % {m} + 1)::BIGINT AS label FROM p")

    def whole(self) -> "Chain":
        return self.add("lab", f"SELECT point_id, {cols(self.d)}, 1::BIGINT AS label FROM p")

    def start(self, ids: Sequence[int] | None = None, rows: Sequence[Sequence[float]] | None = None) -> "Chain":
        if ids is not None:
            at = " UNION ALL ".join(f"SELECT {k} k, {', '.join(f'c{i}::DOUBLE x{i}' for i in range(self.d))} FROM p WHERE point_id = {i_}" for k, i_ in enumerate(ids))
        else:
            at = " UNION ALL ".join(f"SELECT {k} k, " + ", ".join(f"{float(v)!r}::DOUBLE x{i}" for i, v in enumerate(r)) for k, r in enumerate(rows))
        return self.add("init", at)

    def d2(self, x: str = "x", a: str = "c") -> str:
        return " + ".join(f"({a}{i} - {x}{i}) * ({a}{i} - {x}{i})" for i in range(self.d))

    def rounds(self, n: int, labels: str = "true") -> "Chain":
        """`n` updates of every subset, then `cand`: its centroids with members, sse and asse."""
        d, x = self.d, cols(self.d, "x")
        self.add("m0", f"SELECT l.label s, k, {x} FROM (SELECT DISTINCT label FROM lab WHERE {labels}) l, init")
        for r in range(1, n + 2):
            self.add(f"a{r}", f"SELECT s, point_id, {cols(d)}, min({{'d': {self.d2()}, 'k': k}}) b FROM lab JOIN m{r - 1} ON s = label GROUP BY s, point_id, {cols(d)}")
            if r <= n:
                means = ", ".join(f"sum(c{i})::DOUBLE / count(*) y{i}" for i in range(d))
                kept = ", ".join(f"coalesce(y{i}, x{i}) x{i}" for i in range(d))
                self.add(f"m{r}", f"SELECT s, k, {kept} FROM m{r - 1} LEFT JOIN (SELECT s, b.k k, {means} FROM a{r} GROUP BY 1, 2) USING (s, k)")
        self.add("own", f"SELECT s, b.k k, count(*) members, sum(floor(b.d)::BIGINT)::BIGINT sse FROM a{n + 1} GROUP BY 1, 2")
        self.add("per", f"SELECT s, sum(floor(b.d)::BIGINT)::DOUBLE / count(*) asse, sum(sqrt(b.d)) / count(*) asse_dist, count(*) n FROM a{n + 1} GROUP BY 1")
        return self.add("cand", f"SELECT s subset_id, k cluster_id, {', '.join(f'x{i} c{i}' for i in range(d))}, coalesce(members, 0)::BIGINT members, coalesce(sse, 0)::BIGINT sse, asse, asse_dist, n FROM m{n} LEFT JOIN own USING (s, k) JOIN per USING (s)")

    def settled(self, n: int) -> "Chain":
        """After `rounds(n)`: the first round of each subset that moved no centroid."""
        moved = " OR ".join(f"a.x{i} <> b.x{i}" for i in range(self.d))
        each = " UNION ALL ".join(f"SELECT a.s, {r} r, bool_or({moved}) moved FROM m{r - 1} a JOIN m{r} b USING (s, k) GROUP BY a.s" for r in range(1, n + 1))
        return self.add("settled", f"SELECT s, min(r) FILTER (NOT moved) rounds FROM ({each}) GROUP BY s")

    def best(self, by: str = "asse") -> "Chain":
        self.add("top", f"SELECT min({{'e': {by}, 's': subset_id}}).s s FROM cand")
        return self.add("model", f"SELECT cluster_id, {cols(self.d)} FROM cand, top WHERE subset_id = s")

    def merged(self, n: int, k: int) -> "Chain":
        """Hierarchical merging of `n` candidates, unrolled."""
        d = self.d
        c = cols(d)
        self.add("h0", f"SELECT row_number() OVER (ORDER BY subset_id, cluster_id) - 1 id, {c} FROM cand")
        for step in range(n - k):
            d2 = " + ".join(f"(a.c{i} - b.c{i}) * (a.c{i} - b.c{i})" for i in range(d))
            self.add(f"q{step}", f"SELECT min({{'d': {d2}, 'i': a.id, 'j': b.id}}) q FROM h{step} a JOIN h{step} b ON a.id < b.id")
            middle = ", ".join(f"(a.c{i} + b.c{i}) / 2" for i in range(d))
            self.add(f"h{step + 1}", f"SELECT id, {c} FROM h{step}, q{step} WHERE id <> q.i AND id <> q.j UNION ALL SELECT {n + step}, {middle} FROM q{step} JOIN h{step} a ON a.id = q.i JOIN h{step} b ON b.id = q.j")
        return self.add("model", f"SELECT (row_number() OVER (ORDER BY id) - 1)::INT cluster_id, {c} FROM h{n - k}")

    def scored(self, name: str = "scored", model: str = "model") -> "Chain":
        d2 = " + ".join(f"(p.c{i} - m.c{i}) * (p.c{i} - m.c{i})" for i in range(self.d))
        return self.add(name, f"SELECT point_id, {', '.join(f'p.c{i}' for i in range(self.d))}, min({{'d': {d2}, 'k': cluster_id}}) b FROM p, {model} m GROUP BY ALL")


SSE = "SELECT sum(floor(b.d)::BIGINT)::BIGINT sse FROM scored"


def started(fixture: str, number: int = 1) -> Sequence[int]:
    return INITIAL[number]
