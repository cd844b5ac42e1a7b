"""SQL that runs the iterations themselves, for checks in another engine: a few steps of every method at rank two,
over all nodes and all components, as a chain of tables (node, i, k, v).

Nothing here is used by the methods. The network is the random one of ten nodes whose edges are drawn by md5.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np


def edges_sql(n: int, p: float, seed: int) -> str:
    fraction = f"(CAST(('0x' || substr(md5('{seed}|' || a.i || '|' || b.i), 1, 8)) AS BIGINT) / 4294967296.0)"
    return f"SELECT CAST(a.i AS INT) AS src, CAST(b.i AS INT) AS dst FROM range({n}) a(i), range({n}) b(i) WHERE a.i < b.i AND {fraction} < {p}"


def weights_ctes(n: int, p: float, seed: int) -> str:
    """Tables e (edges) and w (local-degree weights, both ways and the diagonal)."""
    return f"""e AS MATERIALIZED ({edges_sql(n, p, seed)}), eb AS MATERIALIZED (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), ed AS MATERIALIZED (SELECT src, count(*) AS deg FROM eb GROUP BY src),
 eo AS MATERIALIZED (SELECT eb.src, eb.dst, 1e0 / greatest(x.deg, y.deg) AS w FROM eb JOIN ed x ON x.src = eb.src JOIN ed y ON y.src = eb.dst),
 w AS MATERIALIZED (SELECT src, dst, w FROM eo UNION ALL SELECT CAST(i AS INT), CAST(i AS INT), 1e0 - coalesce((SELECT sum(w) FROM eo WHERE eo.src = i), 0e0) FROM range({n}) n(i))"""


def moments_ctes(n: int, d: int) -> str:
    """Tables m (node matrices of the embeddings by vec_id, about the mean of all, whose mean is the covariance) and c
    (the covariance)."""
    return f"""x AS MATERIALIZED (SELECT vec_id, CAST(vec_id % {n} AS INT) AS node, CAST(i AS INT) AS i, CAST(embedding[i + 1] AS DOUBLE) AS v FROM embeddings, range({d}) r(i)),
 mu AS MATERIALIZED (SELECT i, avg(v) AS m, CAST(count(*) AS DOUBLE) AS n FROM x GROUP BY i), xc AS MATERIALIZED (SELECT vec_id, node, x.i, v - m AS v, n FROM x JOIN mu ON mu.i = x.i),
 m AS MATERIALIZED (SELECT a.node, a.i, b.i AS j, sum(a.v * b.v) * {n} / max(a.n) AS v FROM xc a JOIN xc b ON a.vec_id = b.vec_id GROUP BY a.node, a.i, b.i),
 c AS MATERIALIZED (SELECT i, j, sum(v) / {n} AS v FROM m GROUP BY i, j)"""


class Chain:
    """Tables under construction; every method adds one or more and returns the name of the last."""

    def __init__(self, n: int = 10, d: int = 64, p: float = 0.5, seed: int = 1):
        self.n, self.d = n, d
        self.parts = [weights_ctes(n, p, seed), moments_ctes(n, d)]
        self.anchors: dict[int, str] = {}

    def add(self, sql: str) -> str:
        name = f"t{len(self.parts)}"
        self.parts.append(f"{name} AS MATERIALIZED ({sql})")
        return name

    def axes(self, nodes: int) -> str:
        return self.add(f"SELECT CAST(o AS INT) AS node, CAST(i AS INT) AS i, CAST(k AS INT) AS k, CASE WHEN i = k THEN 1e0 ELSE 0e0 END AS v FROM range({nodes}) o(o), range({self.d}) i(i), range(2) k(k)")

    def product(self, q: str) -> str:
        return self.add(f"SELECT m.node, m.i, q.k, sum(m.v * q.v) AS v FROM m JOIN {q} q ON q.node = m.node AND q.i = m.j GROUP BY m.node, m.i, q.k")

    def central_product(self, q: str) -> str:
        return self.add(f"SELECT q.node, c.i, q.k, sum(c.v * q.v) AS v FROM c JOIN {q} q ON q.i = c.j GROUP BY q.node, c.i, q.k")

    def mixed(self, z: str, rounds: int) -> str:
        for _ in range(rounds):
            z = self.add(f"SELECT w.dst AS node, i, k, sum(w.w * v) AS v FROM {z} z JOIN w ON w.src = z.node GROUP BY w.dst, i, k")
        return z

    def anchor(self, rounds: int) -> str:
        """First column of the power: what a node reads a sum by."""
        if rounds not in self.anchors:
            if rounds == 0:
                self.anchors[0] = self.add(f"SELECT CAST(i AS INT) AS node, CASE WHEN i = 0 THEN 1e0 ELSE 0e0 END AS v FROM range({self.n}) r(i)")
            else:
                before = self.anchor(rounds - 1)
                self.anchors[rounds] = self.add(f"SELECT w.dst AS node, sum(w.w * v) AS v FROM {before} z JOIN w ON w.src = z.node GROUP BY w.dst")
        return self.anchors[rounds]

    def summed(self, z: str, rounds: int) -> str:
        a = self.anchor(rounds)
        z = self.mixed(z, rounds)
        return self.add(f"SELECT z.node, i, k, z.v * CASE WHEN a.v > 1e-12 THEN 1e0 / a.v ELSE {self.n}e0 END AS v FROM {z} z JOIN {a} a ON a.node = z.node")

    def combined(self, *terms: tuple[str, float]) -> str:
        both = " UNION ALL ".join(f"SELECT node, i, k, v * {s!r}::DOUBLE AS v FROM {t}" for t, s in terms)
        return self.add(f"SELECT node, i, k, sum(v) AS v FROM ({both}) GROUP BY node, i, k")

    def column(self, z: str, k: int) -> str:
        return self.add(f"SELECT node, i, {k} AS k, v FROM {z} WHERE k = {k}")

    def unit(self, z: str) -> str:
        return self.add(f"SELECT z.node, i, k, v / s AS v FROM {z} z JOIN (SELECT node, sqrt(sum(v * v)) AS s FROM {z} GROUP BY node) n ON n.node = z.node")

    def without(self, z: str, q: str) -> str:
        """A column less its part along another, which is a unit vector."""
        dot = self.add(f"SELECT z.node, sum(z.v * q.v) AS s FROM {z} z JOIN {q} q ON q.node = z.node AND q.i = z.i GROUP BY z.node")
        return self.add(f"SELECT z.node, z.i, z.k, z.v - d.s * q.v AS v FROM {z} z JOIN {q} q ON q.node = z.node AND q.i = z.i JOIN {dot} d ON d.node = z.node")

    def orthonormal(self, z: str) -> str:
        first = self.unit(self.column(z, 0))
        second = self.unit(self.without(self.column(z, 1), first))
        return self.add(f"SELECT * FROM {first} UNION ALL SELECT * FROM {second}")

    # ------------------------------------------------------------ methods

    def row_split(self, rounds: Sequence[int]) -> str:
        q = self.axes(self.n)
        for k in rounds:
            q = self.orthonormal(self.summed(self.product(q), k))
        return q

    def central(self, steps: int) -> str:
        q = self.axes(1)
        for _ in range(steps):
            q = self.orthonormal(self.central_product(q))
        return q

    def central_sequential(self, per: int) -> str:
        q, found = self.axes(1), []
        for k in (0, 1):
            x = self.column(q, k)
            for _ in range(per):
                x = self.central_product(x)
                for f in found:
                    x = self.without(x, f)
                x = self.unit(x)
            found.append(x)
        return self.add(" UNION ALL ".join(f"SELECT * FROM {f}" for f in found))

    def sequential(self, rounds: int, per: int) -> str:
        q, found = self.axes(self.n), []
        for k in (0, 1):
            x = self.column(q, k)
            for _ in range(per):
                x = self.summed(self.product(x), rounds)
                for f in found:
                    x = self.without(x, f)
                x = self.unit(x)
            found.append(x)
        return self.add(" UNION ALL ".join(f"SELECT * FROM {f}" for f in found))

    def hebbian(self, steps: int, step: float) -> str:
        q = self.axes(self.n)
        for _ in range(steps):
            mq = self.product(q)
            corner = self.add(f"SELECT a.node, a.k AS a, b.k AS b, sum(a.v * b.v) AS s FROM {q} a JOIN {mq} b ON a.node = b.node AND a.i = b.i WHERE a.k <= b.k GROUP BY a.node, a.k, b.k")
            part = self.add(f"SELECT q.node, q.i, s.b AS k, sum(q.v * s.s) AS v FROM {q} q JOIN {corner} s ON s.node = q.node AND s.a = q.k GROUP BY q.node, q.i, s.b")
            q = self.combined((self.mixed(q, 1), 1.0), (mq, step), (part, -step))
        return self.orthonormal(q)

    def projected_gradient(self, steps: int, step: float) -> str:
        q = self.axes(self.n)
        for _ in range(steps):
            q = self.orthonormal(self.combined((self.mixed(q, 1), 1.0), (self.product(q), step)))
        return q

    def tracking(self, steps: int, rounds: int) -> str:
        q = self.axes(self.n)
        product = tracker = self.product(q)
        for _ in range(steps):
            tracker = self.mixed(tracker, rounds)
            q = self.orthonormal(tracker)
            now = self.product(q)
            tracker, product = self.combined((tracker, 1.0), (now, 1.0), (product, -1.0)), now
        return q

    # ------------------------------------------------------------ columns

    def holders(self, blocks: Sequence[np.ndarray]) -> str:
        rows = ", ".join(f"({int(i)}, {n})" for n, b in enumerate(blocks) for i in b)
        return self.add(f"SELECT i, holder FROM (VALUES {rows}) AS h(i, holder)")

    def column_product(self, q: str, h: str, rounds: int) -> str:
        """Holders' products with their own columns, summed over the network; each holder keeps its own rows."""
        parts = self.add(f"SELECT h.holder AS node, c.i, q.k, sum(c.v * q.v) AS v FROM c JOIN {q} q ON q.i = c.j JOIN {h} h ON h.i = c.j GROUP BY h.holder, c.i, q.k")
        return self.own_rows(self.summed(parts, rounds), h)

    def own_rows(self, z: str, h: str) -> str:
        return self.add(f"SELECT z.node, z.i, z.k, z.v / {self.n} AS v FROM {z} z JOIN {h} h ON h.i = z.i AND h.holder = z.node")

    def agreed(self, z: str, rounds: int | None) -> str:
        """Holders' numbers (node, i, k, v), summed exactly or as averaging rounds see it."""
        if rounds is None:
            total = self.add(f"SELECT i, k, sum(v) AS v FROM {z} GROUP BY i, k")
            return self.add(f"SELECT CAST(o AS INT) AS node, i, k, v FROM {total}, range({self.n}) o(o)")
        mixed = self.mixed(z, rounds)
        return self.add(f"SELECT node, i, k, v * {self.n} AS v FROM {mixed}")

    def gram_qr(self, v: str, rounds: int | None) -> str:
        grams = self.add(f"SELECT a.node, a.k AS i, b.k AS k, sum(a.v * b.v) AS v FROM {v} a JOIN {v} b ON a.node = b.node AND a.i = b.i GROUP BY a.node, a.k, b.k")
        g = self.agreed(grams, rounds)
        r = self.add(f"SELECT node, sqrt(a) AS r11, b / sqrt(a) AS r12, sqrt(c - b * b / a) AS r22 FROM (SELECT node, max(v) FILTER (WHERE i = 0 AND k = 0) AS a, max(v) FILTER (WHERE i = 0 AND k = 1) AS b, max(v) FILTER (WHERE i = 1 AND k = 1) AS c FROM {g} GROUP BY node)")
        wide = f"(SELECT node, i, max(v) FILTER (WHERE k = 0) AS a, max(v) FILTER (WHERE k = 1) AS b FROM {v} GROUP BY node, i)"
        return self.add(f"SELECT v.node, i, 0 AS k, a / r11 AS v FROM {wide} v JOIN {r} r ON r.node = v.node UNION ALL SELECT v.node, i, 1, (b - r12 * a / r11) / r22 FROM {wide} v JOIN {r} r ON r.node = v.node")

    def own_unit(self, z: str, rounds: int | None) -> str:
        """A column divided by its norm as each holder sees it."""
        squares = self.agreed(self.add(f"SELECT node, 0 AS i, 0 AS k, sum(v * v) AS v FROM {z} GROUP BY node"), rounds)
        return self.add(f"SELECT z.node, z.i, z.k, z.v / sqrt(n.v) AS v FROM {z} z JOIN {squares} n ON n.node = z.node")

    def own_without(self, z: str, q: str, rounds: int | None) -> str:
        dots = self.agreed(self.add(f"SELECT z.node, 0 AS i, 0 AS k, sum(z.v * q.v) AS v FROM {z} z JOIN {q} q ON q.node = z.node AND q.i = z.i GROUP BY z.node"), rounds)
        return self.add(f"SELECT z.node, z.i, z.k, z.v - d.v * q.v AS v FROM {z} z JOIN {q} q ON q.node = z.node AND q.i = z.i JOIN {dots} d ON d.node = z.node")

    def gram_schmidt(self, v: str, rounds: int | None) -> str:
        first = self.own_unit(self.column(v, 0), rounds)
        second = self.own_unit(self.own_without(self.column(v, 1), first, rounds), rounds)
        return self.add(f"SELECT * FROM {first} UNION ALL SELECT * FROM {second}")

    def column_start(self, h: str) -> str:
        return self.add(f"SELECT h.holder AS node, CAST(h.i AS INT) AS i, CAST(k AS INT) AS k, CASE WHEN h.i = k THEN 1e0 ELSE 0e0 END AS v FROM {h} h, range(2) k(k)")

    def column_split(self, blocks, rounds: Sequence[int], agree: int | None, qr: str = "gram") -> str:
        h = self.holders(blocks)
        q = self.column_start(h)
        for k in rounds:
            v = self.column_product(q, h, k)
            q = self.gram_qr(v, agree) if qr == "gram" else self.gram_schmidt(v, agree)
        return q

    def column_sequential(self, blocks, rounds: int, per: int, agree: int | None) -> str:
        h = self.holders(blocks)
        q, found = self.column_start(h), []
        for k in (0, 1):
            x = self.column(q, k)
            for _ in range(per):
                x = self.column_product(x, h, rounds)
                for f in found:
                    x = self.own_without(x, f, agree)
                x = self.own_unit(x, agree)
            found.append(x)
        both = self.add(" UNION ALL ".join(f"SELECT * FROM {f}" for f in found))
        whole = self.add(f"SELECT 0 AS node, i, k, v FROM {both}")
        return self.orthonormal(whole)

    def block_split(self, blocks, rounds: Sequence[int]) -> str:
        """Products of row nodes with each holder's part of the basis, averaged over the row network as its first
        node sees it, then over the holders."""
        h = self.holders(blocks)
        q = self.column_start(h)
        for k in rounds:
            z = self.add(f"SELECT m.node, h.holder * {self.d} + m.i AS i, q.k, sum(m.v * q.v) AS v FROM m JOIN {q} q ON q.i = m.j JOIN {h} h ON h.i = m.j GROUP BY m.node, h.holder, m.i, q.k")
            z = self.mixed(z, k)
            parts = self.add(f"SELECT CAST(i // {self.d} AS INT) AS node, CAST(i % {self.d} AS INT) AS i, k, v FROM {z} WHERE node = 0")
            q = self.gram_qr(self.own_rows(self.summed(parts, k), h), max(k, 1))
        return q

    # ------------------------------------------------------------ results

    def select(self, q: str, node: str = "node") -> str:
        return f"WITH {', '.join(self.parts)} SELECT {node} AS node, CAST(i AS INT) AS i, CAST(k AS INT) AS k, round(v, 6) + 0e0 AS q FROM {q}"

    def measures(self, q: str, truth: str) -> str:
        """Error, lost variance, defect and distances of every node's basis from another basis (node 0) and from the
        mean of all."""
        cross = self.add(f"SELECT q.node, sum(s * s) AS s FROM (SELECT q.node, q.k AS a, t.k AS b, sum(q.v * t.v) AS s FROM {q} q JOIN {truth} t ON t.i = q.i GROUP BY q.node, q.k, t.k) q GROUP BY q.node")
        kept = self.add(f"SELECT q.node, sum(q.v * c.v * p.v) AS s FROM {q} q JOIN c ON c.i = q.i JOIN {q} p ON p.node = q.node AND p.i = c.j AND p.k = q.k GROUP BY q.node")
        gram = self.add(f"SELECT node, max(abs(s - CASE WHEN a = b THEN 1e0 ELSE 0e0 END)) AS s FROM (SELECT a.node, a.k AS a, b.k AS b, sum(a.v * b.v) AS s FROM {q} a JOIN {q} b ON a.node = b.node AND a.i = b.i GROUP BY a.node, a.k, b.k) GROUP BY node")
        far = self.add(f"SELECT q.node, sqrt(sum((q.v - t.v) ** 2)) AS s FROM {q} q JOIN {truth} t ON t.i = q.i AND t.k = q.k GROUP BY q.node")
        off = self.add(f"SELECT max(s) AS s FROM (SELECT q.node, sqrt(sum((q.v - a.v) ** 2)) AS s FROM {q} q JOIN (SELECT i, k, avg(v) AS v FROM {q} GROUP BY i, k) a ON a.i = q.i AND a.k = q.k GROUP BY q.node)")
        return f"""WITH {', '.join(self.parts)} SELECT x.node, round(1 - x.s / 2, 6) + 0e0 AS error, round((SELECT sum(v) FROM c WHERE i = j) - k.s, 6) + 0e0 AS lost, round(g.s, 6) + 0e0 AS defect, round(f.s, 6) + 0e0 AS from_central,
 round((SELECT s FROM {off}), 6) + 0e0 AS disagreement FROM {cross} x JOIN {kept} k ON k.node = x.node JOIN {gram} g ON g.node = x.node JOIN {far} f ON f.node = x.node"""
