"""Graph kernels on the user-item graph, solved for the test users only: never an inverse of all nodes."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.storagelevel import StorageLevel

from .gram import pack_rows
from .model import _key_type, best_n, item_index

#: Parameter ranges of the comparison.
GRID = {
    "lapinv": [{}],
    "forest": [{}],
    "diffusion": [{"t": t} for t in (*range(1, 11), 50, 100)],
    "entropy": [{"t": t} for t in (*range(1, 11), 50, 100)],
    "commute": [{"damping": a} for a in (1e-6, 1e-5, 1e-4, 1e-3, 1e-2, 0.1, 0.5, 0.9, 0.99)],
}
BLOCK = 256  # users solved together
MOST_EDGES = 50_000_000  # of a graph that is broadcast
#: Users and cells of a biadjacency matrix that the driver holds densely.
DENSE_USERS, DENSE_CELLS = 4_000, 50_000_000
#: Cells up to which every worker gets the dense form, and bytes of a task's vectors over all nodes and of the edges that it multiplies at once (those stay in a core's cache).
WORKER_CELLS, VECTOR_BYTES, EDGE_BYTES = 10_000_000, 150_000_000, 1_000_000
#: Rows that are summed up together, edges beyond which a row goes alone, users whose systems are solved together.
ROWS, LONG, SOLVED = 512, 2048, 64
FOLLOWED = 16  # an edge that is followed alone takes as long as so many of a product
LEADING = 24  # columns that the driver works out ahead of the solves
EDGES_AT_ONCE = 1_000_000  # of those whose ends the driver compares


class Sums:
    """Sums of a matrix' rows by a sparse matrix of 0 and 1, or of values. Rows of many edges go one by one; the others stand by falling number of edges in
    groups of ROWS, whose first edges come first, then their second ones, and so on: a gather and an addition serve a whole group."""

    def __init__(self, at: np.ndarray, degree: np.ndarray, value: np.ndarray | None):
        self.degree, begin = degree, np.cumsum(degree) - degree
        self.order = np.argsort(-degree, kind="stable").astype(np.int32)
        self.order = self.order[: np.count_nonzero(degree)]
        self.long = int(np.count_nonzero(degree > LONG))
        self.at, self.value = np.empty(len(at), np.int32), None if value is None else np.empty(len(at))
        self.live, self.begin, to = [], [], 0  # of each group: rows that have so many edges and more, and where it begins
        for a, b in self.groups():
            rows, most = self.order[a:b], degree[self.order[a]] if b > a + 1 or a >= self.long else 0
            if most:
                # by edge, then by row
                deg = degree[rows]
                self.live.append(len(rows) - np.searchsorted(deg[::-1], np.arange(most), side="right"))
                level = np.arange(deg.sum()) - np.repeat(np.cumsum(deg) - deg, deg)
                pick = (np.repeat(begin[rows], deg) + level)[np.argsort(level, kind="stable")]
            else:
                pick = slice(begin[rows[0]], begin[rows[0]] + degree[rows[0]])
            size = int(degree[rows].sum())
            self.at[to : to + size] = at[pick]
            if value is not None:
                self.value[to : to + size] = value[pick]
            self.begin.append(to)
            to += size
        self.place = np.empty(len(degree), np.int32)
        self.place[self.order] = np.arange(len(self.order))

    def groups(self):
        yield from ((a, a + 1) for a in range(self.long))
        yield from ((a, min(len(self.order), a + ROWS)) for a in range(self.long, len(self.order), ROWS))

    def row(self, row: int) -> np.ndarray:
        """Edges of a row, in their order."""
        p, size = int(self.place[row]), int(self.degree[row])
        if p < self.long or not size:
            return self.at[self.begin[p] : self.begin[p] + size] if size else self.at[:0]
        group = (p - self.long) // ROWS
        live = self.live[group][:size]
        return self.at[self.begin[self.long + group] + (p - self.long) % ROWS + np.cumsum(live) - live]

    def __call__(self, x: np.ndarray) -> np.ndarray:
        out, to = np.zeros((len(self.degree), x.shape[1])), 0
        x = np.ascontiguousarray(x)
        step = int(max(1, EDGE_BYTES // (8 * x.shape[1])))
        space = np.empty((min(step, max(LONG, ROWS)), x.shape[1]))
        step = len(space)

        def terms(a, b):
            part = np.take(x, self.at[a:b], axis=0, out=space[: b - a], mode="clip")
            if self.value is not None:
                part *= self.value[a:b, None]
            return part

        for row in self.order[: self.long].tolist():
            end = to + int(self.degree[row])
            for a in range(to, end, step):
                out[row] += terms(a, min(end, a + step)).sum(0)
            to = end
        for k, live in enumerate(self.live):
            rows = self.order[self.long + k * ROWS :][:ROWS]
            total = np.zeros((len(rows), x.shape[1]))
            for n in live.tolist():
                for a in range(0, n, step):
                    b = min(n, a + step)
                    total[a:b] += terms(to + a, to + b)
                to += n
            out[rows] = total
        return out


class Edges:
    """A sparse matrix by rows and by columns, with four bytes an edge each way (eight by rows) where all values are 1."""

    def __init__(self, row: np.ndarray, column: np.ndarray, value: np.ndarray | None, shape: tuple[int, int]):
        if value is not None and bool((value == 1).all()):
            value = None
        # gathered edges are in order already: nothing of their number is copied for it
        if not bool(((row[1:] > row[:-1]) | (row[1:] == row[:-1]) & (column[1:] >= column[:-1])).all()):
            order = np.lexsort((column, row))
            row, column, value = row[order], column[order], None if value is None else value[order]
        self.at, count = column.astype(np.int32), np.bincount(row, minlength=shape[0])
        self.ends, self.value, self.shape = np.cumsum(count), value, shape
        self.dot = Sums(self.at, count, value)
        self.count = count
        back = np.argsort(column, kind="stable")
        self.tdot = Sums(row[back], np.bincount(column, minlength=shape[1]), None if value is None else value[back])

    def raters(self, column: int) -> np.ndarray:
        return self.tdot.row(column)

    def own(self, row: int) -> np.ndarray:
        return self.at[self.ends[row - 1] if row else 0 : self.ends[row]]

    def dense(self) -> np.ndarray:
        out = np.zeros(self.shape)
        out[np.repeat(np.arange(self.shape[0]), np.diff(self.ends, prepend=0)), self.at] = 1 if self.value is None else self.value
        return out


class Graph:
    """Nodes: users first, then items; one edge a rating, of weight 1 unless ``weighted``."""

    def __init__(self, row: np.ndarray, column: np.ndarray, value: np.ndarray | None, n: int, m: int):
        self.r, self.n, self.m = Edges(row, column, value, (n, m)), n, m
        self.degree = np.concatenate([np.bincount(row, weights=value, minlength=n), np.bincount(column, weights=value, minlength=m)])
        self.component = self._components(row, column)
        self.near: tuple[np.ndarray, np.ndarray] | None = None  # of the system that is to be solved

    def _components(self, row, column) -> np.ndarray:
        label = np.arange(self.n + self.m)
        while True:
            low = label.copy()
            for a in range(0, len(row), EDGES_AT_ONCE):
                user, item = row[a : a + EDGES_AT_ONCE], self.n + column[a : a + EDGES_AT_ONCE]
                np.minimum.at(low, user, label[item])
                np.minimum.at(low, item, low[user])
            low = low[low]
            if (low == label).all():
                return np.unique(label, return_inverse=True)[1]
            label = low

    def width(self, arrays: int = 12) -> int:
        """Vectors over all nodes that a task takes at once, where it holds so many arrays of them."""
        return int(max(1, min(BLOCK, VECTOR_BYTES // (8 * arrays * (self.n + self.m)))))

    def solved(self) -> int:
        """Users whose systems a task solves at once: conjugate gradients hold vectors over the users, a few over the items."""
        return int(max(1, min(SOLVED, VECTOR_BYTES // (8 * (9 * self.n + 4 * self.m)))))

    def listed(self) -> int:
        """Users whose scores of all items a task holds at once."""
        return int(max(1, VECTOR_BYTES // (8 * self.m)))

    def adjacent(self, x: np.ndarray) -> np.ndarray:
        return np.vstack([self.r.dot(x[self.n :]), self.r.tdot(x[: self.n])])

    def forward(self, x: np.ndarray) -> np.ndarray:
        """P x with P = D^-1 A."""
        return self.adjacent(x) / np.maximum(self.degree, 1e-300)[:, None]

    def backward(self, x: np.ndarray) -> np.ndarray:
        return self.adjacent(x / np.maximum(self.degree, 1e-300)[:, None])

    def units(self, nodes: np.ndarray) -> np.ndarray:
        e = np.zeros((self.n + self.m, len(nodes)))
        e[nodes, np.arange(len(nodes))] = 1
        return e

    def centred(self, x: np.ndarray) -> np.ndarray:
        """Without the mean of each component."""
        count = np.bincount(self.component)
        mean = np.stack([np.bincount(self.component, weights=c) / count for c in x.T], 1)
        return x - mean[self.component]


def block_cg(apply, b: np.ndarray, diagonal: np.ndarray, tol: float = 1e-12, most: int = 5000, near: tuple[np.ndarray, np.ndarray] | None = None) -> np.ndarray:
    """Conjugate gradients for many right-hand sides at once, with a diagonal preconditioner; ``near``: columns and weights of what the diagonal leaves slow."""

    def eased(r: np.ndarray, out: np.ndarray | None = None) -> np.ndarray:
        z = np.divide(r, diagonal[:, None], out=out)
        if near:
            z += near[0] @ (near[1][:, None] * (near[0].T @ r))
        return z

    x, r = np.zeros_like(b), b.copy()
    z = eased(r)
    p, rz = z.copy(), np.einsum("ij,ij->j", r, z)
    goal = tol * np.maximum(np.linalg.norm(b, axis=0), 1e-300)
    for _ in range(most):
        live = np.sqrt(np.einsum("ij,ij->j", r, r)) > goal
        if not live.any():
            break
        ap = apply(p)
        step = np.where(live, rz / np.where(live, np.einsum("ij,ij->j", p, ap), 1), 0)
        x += np.multiply(p, step, out=z)
        r -= np.multiply(ap, step, out=ap)
        eased(r, out=z)
        fresh = np.einsum("ij,ij->j", r, z)
        p *= np.where(live, fresh / np.where(rz > 0, rz, 1), 0)
        p += z
        rz = fresh
    return x


def schur(graph: Graph, left: np.ndarray, inner: np.ndarray):
    """p -> left p - R inner R' p, for vectors over the users."""

    def apply(p: np.ndarray) -> np.ndarray:
        items = graph.r.tdot(p)
        items *= inner[:, None]
        out = graph.r.dot(items)
        np.negative(out, out=out)
        out += p * left[:, None]
        return out

    return apply


def system(graph: Graph, kind: str, damping: float = 0.5) -> tuple[np.ndarray, np.ndarray]:
    """left and inner of the system over the users that a kernel solves once the items are eliminated."""
    du, di = graph.degree[: graph.n], graph.degree[graph.n :]
    if kind == "lapinv":
        return np.maximum(du, 1e-12), np.where(di > 0, 1 / np.maximum(di, 1e-300), 0)
    if kind == "forest":
        return 1 + du, 1 / (1 + di)
    if kind == "commute":
        return np.maximum(du, 1e-12), damping**2 / np.maximum(di, 1e-12)
    raise ValueError(kind)


def leading(graph: Graph, left: np.ndarray, inner: np.ndarray, k: int = LEADING, steps: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """For ``near``: the system scaled by the roots of ``left`` is I - N, and the few largest values of N are what conjugate gradients take long for.

    Any columns and positive weights leave the solution as it is, so a few steps of subspace iteration do; a value of 1 (a component's mean) is held off.
    """
    root, k = np.sqrt(left)[:, None], min(k, graph.n)

    def step(x: np.ndarray) -> np.ndarray:
        items = graph.r.tdot(x / root)
        items *= inner[:, None]
        return graph.r.dot(items) / root

    x = np.random.default_rng(11).standard_normal((graph.n, k))
    for _ in range(steps):
        x = np.linalg.qr(step(x))[0]
    at, turn = np.linalg.eigh(x.T @ step(x))
    at = np.clip(at, 0, 1)
    return (x @ turn) / root, np.where(at < 1 - 1e-9, 1 / np.maximum(1 - at, 1e-4) - 1, 0)


def averaged(step, x: np.ndarray, t: int) -> np.ndarray:
    total = np.zeros_like(x)
    for _ in range(t):
        x = step(x)
        total += x
    return total / t


def user_rows(graph: Graph, kind: str, users: np.ndarray, t: int = 2, damping: float = 0.5, eps: float = 1e-12) -> np.ndarray:
    """Kernel entries of the given users (rows) and all items (columns)."""
    if kind == "diffusion":
        return averaged(graph.forward, averaged(graph.backward, graph.units(users), t), t)[graph.n :].T
    if kind == "entropy":
        return entropy_rows(graph, users, t, eps)
    # the items are eliminated, so that the conjugate gradients go over the user side only
    r, (left, inner) = graph.r, system(graph, kind, damping)
    if kind == "lapinv":
        right = graph.centred(graph.units(users))
        x = block_cg(schur(graph, left, inner), right[: graph.n] + r.dot(inner[:, None] * right[graph.n :]), left, near=graph.near)
        whole = graph.centred(np.vstack([x, inner[:, None] * (right[graph.n :] + r.tdot(x))]))
        return np.where(graph.component[:, None] == graph.component[users][None, :], whole, 0)[graph.n :].T
    e = np.zeros((graph.n, len(users)))
    e[users, np.arange(len(users))] = 1
    out = r.tdot(block_cg(schur(graph, left, inner), e, left, near=graph.near))
    out *= (inner / (damping if kind == "commute" else 1))[:, None]
    return out.T


def entropy_rows(graph: Graph, users: np.ndarray, t: int, eps: float) -> np.ndarray:
    """Symmetrised cross-entropy of the users' and the items' averaged transition rows; zeros are raised to eps before the logarithm."""
    if by_edges(graph, t):
        return entropy_edges(graph, users, t, eps)
    step = graph.width()
    own = np.empty((len(users), graph.n + graph.m))  # rows of Z for the users
    for a in range(0, len(users), step):
        own[a : a + step] = averaged(graph.backward, graph.units(users[a : a + step]), t).T
    log_own = np.maximum(own, eps)
    np.log(log_own, out=log_own)
    out = np.empty((len(users), graph.m))
    for a in range(0, graph.m, step):
        items = np.arange(a, min(graph.m, a + step))
        z = averaged(graph.backward, graph.units(graph.n + items), t)
        out[:, items] = log_own @ z
        np.maximum(z, eps, out=z)
        out[:, items] += own @ np.log(z, out=z)
    return out


def by_edges(graph: Graph, t: int) -> bool:
    return t <= 2 and graph.r.value is None


def near_items(graph: Graph, items: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """R' diag(weight) R for some items (columns), by their own edges alone where these lead to few."""
    r, w = graph.r, len(items)
    sides = [r.raters(i) for i in items]
    v, k = np.concatenate(sides), np.repeat(np.arange(w), [len(x) for x in sides])
    count = r.count[v]
    if count.sum() * FOLLOWED > len(r.at) * w:
        x = np.zeros((graph.n, w))
        x[v, k] = weight[v]
        return r.tdot(x)
    at = np.repeat(r.ends[v] - np.cumsum(count), count) + np.arange(count.sum())
    return np.bincount(r.at[at].astype(np.int64) * w + np.repeat(k, count), np.repeat(weight[v], count), graph.m * w).reshape(graph.m, w)


def entropy_edges(graph: Graph, users: np.ndarray, t: int, eps: float) -> np.ndarray:
    """The entropy of one or two steps by edges: a first step only reaches neighbours, so every sum over nodes is one over the edges of the user or of the item.

    Rows of Z over t steps are 1 / (degree t) on neighbours and, for two steps, a product of R with R' on nodes of the own side; elsewhere 0, raised to eps.
    """
    n, m, r, low, b = graph.n, graph.m, graph.r, np.log(eps), len(users)
    du, di = np.maximum(graph.degree[:n], 1e-300), np.maximum(graph.degree[n:], 1e-300)
    own = [r.own(u) for u in users]
    count = np.array([len(x) for x in own])
    k, j = np.repeat(np.arange(b), count), np.concatenate(own)
    lift_u, lift_i = (np.maximum(np.log(np.maximum(1 / (d * t), eps)) - low, 0) for d in (du, di))
    out, rest = np.empty((m, b)), np.zeros(b)
    # items' rows on their raters and the users' rows on users
    step = min(SOLVED, graph.width())
    for a in range(0, b, step):
        z = np.zeros((n, min(step, b - a)))
        if t > 1:
            e = slice(*np.searchsorted(k, (a, a + step)))
            first = np.zeros((m, z.shape[1]))
            first[j[e], k[e] - a] = 1 / (di[j[e]] * du[users[k[e]]] * t)
            z = r.dot(first)
            rest[a : a + step] = low * z.sum(0)
            out[:, a : a + step] = r.tdot(z) * lift_i[:, None]
        else:
            out[:, a : a + step] = 0
        np.maximum(z, eps, out=z)
        logs = r.tdot(np.log(z, out=z))
        logs /= (di * t)[:, None]
        out[:, a : a + step] += logs
    # users' rows on their items and the items' rows on items
    mine, a_u = Sums(j, count, None), 1 / (du[users] * t)
    items, width = np.argsort(-graph.degree[n:], kind="stable"), min(SOLVED, graph.width(6))
    for a in range(0, m, width):
        i = items[a : a + width]
        if t > 1:
            z = near_items(graph, i, 1 / du)
            z /= di[i] * t
        else:
            z = np.zeros((m, len(i)))
        part = mine(z) * lift_u[users][:, None] + low * z.sum(0)
        np.maximum(z, eps, out=z)
        part += mine(np.log(z, out=z)) * a_u[:, None]
        out[i] += part.T
    out += rest
    return out.T


class DenseGraph:
    """The kernels of a graph whose user side fits a dense matrix, for whole parameter grids at once.

    With the singular value decomposition U s V' of the biadjacency scaled by the roots of both degrees, powers of the transition matrix and
    the damped inverse are functions of s, so one decomposition serves every t and every damping. The Laplacian kernels go
    by the Schur complement on the user side.
    """

    def __init__(self, graph: Graph):
        self.graph, n = graph, graph.n
        self.r = graph.r.dense()
        root = lambda d: np.where(d > 0, 1 / np.sqrt(np.maximum(d, 1e-300)), 0)
        self.du, self.di = graph.degree[:n], graph.degree[n:]
        self.iu, self.ii = root(self.du), root(self.di)
        self.u, self.s, vt = np.linalg.svd(self.iu[:, None] * self.r * self.ii, full_matrices=False)
        self.v = vt.T

    @staticmethod
    def fits(n: int, m: int) -> bool:
        return n <= DENSE_USERS and n * m <= DENSE_CELLS

    def means(self, t: int) -> tuple[np.ndarray, np.ndarray]:
        """Of s to the even and to the odd powers up to t, over t."""
        even, odd, power = np.zeros_like(self.s), np.zeros_like(self.s), np.ones_like(self.s)
        for k in range(1, t + 1):
            power = power * self.s
            if k % 2:
                odd += power
            else:
                even += power
        return even / t, odd / t

    def rows(self, kind: str, users: np.ndarray, t: int = 2, damping: float = 0.5, eps: float = 1e-12) -> np.ndarray:
        """Kernel entries of the given users (rows) and all items (columns)."""
        own, n = self.u[users], self.graph.n
        if kind == "commute":
            return self.iu[users, None] * ((own * (damping * self.s / (1 - (damping * self.s) ** 2))) @ self.v.T) * self.ii
        if kind == "diffusion":
            e, o = self.means(t)
            gu, gi = self.u.T @ (self.du[:, None] * self.u), self.v.T @ (self.di[:, None] * self.v)
            return self.iu[users, None] * ((((own * e) @ gu) * o + ((own * o) @ gi) * e) @ self.v.T) * self.ii
        if kind == "entropy":
            e, o = self.means(t)
            mine = self.iu[users, None] * np.hstack([((own * e) @ self.u.T) * np.sqrt(self.du), ((own * o) @ self.v.T) * np.sqrt(self.di)])
            mine, logs = np.maximum(mine, 0), np.log(np.maximum(mine, eps))
            out = np.empty((len(users), self.graph.m))
            for a in range(0, self.graph.m, 512):
                v = self.v[a : a + 512]
                z = self.ii[a : a + 512, None] * np.hstack([((v * o) @ self.u.T) * np.sqrt(self.du), ((v * e) @ self.v.T) * np.sqrt(self.di)])
                out[:, a : a + 512] = mine @ np.log(np.maximum(z, eps)).T + logs @ np.maximum(z, 0).T
            return out
        e = np.zeros((n, len(users)))
        e[users, np.arange(len(users))] = 1
        if kind == "forest":
            inner = 1 / (1 + self.di)
            x = np.linalg.solve(np.diag(1 + self.du) - (self.r * inner) @ self.r.T, e)
            return (inner[:, None] * (self.r.T @ x)).T
        if kind == "lapinv":
            component, inner = self.graph.component, self.ii**2
            share = 1 / np.bincount(component)
            same = component[:, None] == component[users][None, :]
            right = same * -share[component[users]]
            right[users, np.arange(len(users))] += 1
            at, xi = np.linalg.eigh(np.diag(self.du) - (self.r * inner) @ self.r.T)
            good = at > 1e-10 * max(at[-1], 1e-300)
            x = (xi[:, good] / at[good]) @ (xi[:, good].T @ (right[:n] + self.r @ (inner[:, None] * right[n:])))
            y = inner[:, None] * (right[n:] + self.r.T @ x)
            return np.where(same, self.graph.centred(np.vstack([x, y])), 0)[n:].T
        raise ValueError(kind)


def gathered_graph(ratings: DataFrame, weighted: bool) -> tuple[list, list, Graph]:
    """Sorted keys of users and items and the graph; the edges come to the driver packed, four bytes each (twelve with weights)."""
    items = ratings.select("item_id").distinct().orderBy("item_id").toArrow().column(0).to_pylist()
    key_type = ratings.schema["user_id"]
    schema = T.StructType([key_type, T.StructField("ix", T.BinaryType()), T.StructField("x", T.BinaryType())])

    def packed(batches):
        from pyspark.sql.pandas.types import to_arrow_schema

        out = to_arrow_schema(schema)
        for batch in batches:
            ix, x = batch.column("ix"), batch.column("x")
            at = [np.asarray(v.values, np.int32).tobytes() for v in ix]
            yield pa.RecordBatch.from_arrays([batch.column("user_id").cast(out.field(0).type), pa.array(at, pa.binary()), pa.array([np.asarray(v.values, float).tobytes() if weighted else b"" for v in x], pa.binary())], schema=out)

    rows = pack_rows(ratings, item_index(ratings.sparkSession, items)).mapInArrow(packed, schema).toArrow().sort_by("user_id")
    ix = [np.frombuffer(b.as_py(), np.int32) for b in rows.column("ix")]
    value = np.concatenate([np.frombuffer(b.as_py()) for b in rows.column("x")] or [np.zeros(0)]) if weighted else None
    row = np.repeat(np.arange(len(ix), dtype=np.int32), [len(v) for v in ix])
    users = rows.column("user_id").to_pylist()
    return users, items, Graph(row, np.concatenate(ix or [np.zeros(0, np.int32)]), value, len(users), len(items))


def kernel_scores(ratings: DataFrame, kind: str, users: DataFrame | None = None, weighted: bool = False, top: int | None = None, **how) -> DataFrame:
    """(user_id, item_id, score) of the given users (all by default) and every item, or with ``top`` (user_id, rank, item_id, score) of each user's best
    unrated items, which then are all that leaves a task. The graph is broadcast behind a check of its size, and blocks of users are solved in parallel."""
    spark, level = ratings.sparkSession, ratings.storageLevel
    # counted, indexed and packed in turn: a view is worked out once
    own = None if level.useMemory or level.useDisk else ratings.persist(StorageLevel.DISK_ONLY)
    try:
        edges = ratings.count()
        if edges > MOST_EDGES:
            raise MemoryError(f"{edges} edges exceed the broadcast of {MOST_EDGES}")
        user_keys, item_keys, held = gathered_graph(ratings, weighted)
    finally:
        if own is not None:
            own.unpersist()
    dense = DenseGraph.fits(held.n, held.m) and held.n * held.m <= WORKER_CELLS
    if not dense and kind in ("forest", "commute", "lapinv"):
        held.near = leading(held, *system(held, kind, how.get("damping", 0.5)))
    # users taken at once: the entropy's scores stay while all items pass by, beyond two steps with the users' rows in two arrays
    if kind == "entropy" and not dense:
        block = held.listed() if by_edges(held, how.get("t", 2)) else held.width(4)
    else:
        block = BLOCK if dense else held.width() if kind == "diffusion" else held.solved()
    graph = spark.sparkContext.broadcast(held)
    whole = spark.sparkContext.broadcast(DenseGraph(held)) if dense else None
    place = {k: i for i, k in enumerate(user_keys)}
    wanted = user_keys if users is None else [r[0] for r in users.select("user_id").distinct().collect() if r[0] in place]
    key_type = ratings.schema["user_id"]
    asked = spark.createDataFrame([(k, place[k]) for k in sorted(wanted)], T.StructType([key_type, T.StructField("ix", T.IntegerType())]))
    asked = asked.repartition(max(1, min(64, -(-len(wanted) // block))))
    rank = [T.StructField("rank", T.IntegerType())] if top else []
    schema = T.StructType([key_type, *rank, T.StructField("item_id", _key_type(item_keys)), T.StructField("score", T.DoubleType())])

    def run(batches):
        from pyspark.sql.pandas.types import to_arrow_schema

        out, g = to_arrow_schema(schema), graph.value
        keys = pa.array(item_keys, out.field("item_id").type)
        asked_here = list(batches)  # keys and places only; a block is not cut by the size of a batch
        for batch in pa.Table.from_batches(asked_here).combine_chunks().to_batches() if asked_here else ():
            even = max(1, -(-batch.num_rows // max(1, -(-batch.num_rows // block))))
            for a in range(0, batch.num_rows, even):
                part = batch.slice(a, even)
                at = part.column("ix").to_numpy().astype(np.int64)
                scores = whole.value.rows(kind, at, **how) if dense else user_rows(g, kind, at, **how)
                for user, u, row in zip(part.column("user_id").to_pylist(), at, scores, strict=True):
                    if not top:
                        yield pa.RecordBatch.from_arrays([pa.array([user] * len(row), out.field(0).type), keys, pa.array(row)], schema=out)
                        continue
                    row = row.copy()
                    row[g.r.own(u)] = np.nan
                    best = best_n(row, top)
                    columns = ([user] * len(best), range(1, len(best) + 1), [item_keys[j] for j in best], row[best])
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, out, strict=True)], schema=out)

    return asked.mapInArrow(run, schema)


def kernel_top(ratings: DataFrame, kind: str, n: int = 10, **how) -> DataFrame:
    """(user_id, rank, item_id, score): every user's n best unrated items under a kernel."""
    return kernel_scores(ratings, kind, top=n, **how)


def popularity(ratings: DataFrame, pairs: DataFrame) -> DataFrame:
    counts = ratings.groupBy("item_id").agg(F.count("*").cast("double").alias("score"))
    return pairs.join(counts, "item_id", "left").withColumn("score", F.coalesce("score", F.lit(0.0)))


def random_rank(pairs: DataFrame, seed: int = 97) -> DataFrame:
    """Scores by a hash of their own: that of the splits would put every held-out item last."""
    from proxrec.functions.hashing import fraction

    return pairs.withColumn("score", fraction(seed, "user_id", "item_id"))
