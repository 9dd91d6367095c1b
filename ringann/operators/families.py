"""Hash families. A family turns vectors into code strings; nothing else of it reaches the search."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringann.functions import theory


def matrix(col: pa.Array) -> np.ndarray:
    """List column of equal sizes as float64[n, d]."""
    n = len(col)
    flat = col.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(n, -1) if n else flat.reshape(0, 0)


class Sets:
    """Rows of sorted distinct integers, one after the other: the points of set families."""

    def __init__(self, flat: np.ndarray, off: np.ndarray):
        self.flat, self.off = flat, off

    def __len__(self):
        return len(self.off) - 1

    def __getitem__(self, at):
        if np.isscalar(at):
            return self.flat[self.off[at] : self.off[at + 1]]
        at = np.asarray(at, np.int64)
        size = (self.off[1:] - self.off[:-1])[at]
        off = np.concatenate([[0], np.cumsum(size)]).astype(np.int64)
        inner = np.arange(off[-1]) - np.repeat(off[:-1], size)
        return Sets(self.flat[np.repeat(self.off[at], size) + inner], off)

    @classmethod
    def of(cls, col: pa.Array) -> Sets:
        size = pc.list_value_length(col).to_numpy(zero_copy_only=False)
        flat, row = col.flatten().to_numpy(zero_copy_only=False).astype(np.int64), np.repeat(np.arange(len(col)), size)
        by = np.lexsort((flat, row))
        flat = flat[by]
        first = np.ones(len(flat), bool)
        first[1:] = (flat[1:] != flat[:-1]) | (row[1:] != row[:-1])  # rows stay where they are when sorted
        return cls(flat[first], np.concatenate([[0], np.cumsum(np.bincount(row[first], minlength=len(col)))]).astype(np.int64))

    @classmethod
    def joined(cls, parts: list[Sets]) -> Sets:
        sizes = np.concatenate([np.diff(p.off) for p in parts])
        return cls(np.concatenate([p.flat for p in parts]), np.concatenate([[0], np.cumsum(sizes)]).astype(np.int64))


class Family:
    """Codes of points. `d` is the length of a vector; set families have none."""

    metric = "euclidean"
    m: int
    d: int | None = None

    def points(self, col: pa.Array):
        return matrix(col)

    def codes(self, x: np.ndarray) -> np.ndarray:
        raise NotImplementedError

    def alternatives(self, x: np.ndarray, n_alt: int) -> tuple[np.ndarray, np.ndarray]:
        """(codes, scores), both [n, m, n_alt], scores ascending."""
        raise NotImplementedError

    def collision_prob(self, tau: float) -> float:
        raise NotImplementedError

    def sensitivity(self, r: float, c: float) -> tuple[float, float, float]:
        p1, p2 = self.collision_prob(r), self.collision_prob(c * r)
        return p1, p2, theory.rho(p1, p2)


class RandomProjection(Family):
    """floor((a.x + b) / w); Gaussian a for Euclidean (p=2), Cauchy for Manhattan (p=1)."""

    def __init__(self, d: int, m: int, w: float, seed: int = 0, p: int = 2):
        rng = np.random.Generator(np.random.Philox(seed))
        self.d, self.m, self.w, self.p, self.metric = d, m, w, p, "euclidean" if p == 2 else "manhattan"
        self.a = rng.standard_normal((d, m)) if p == 2 else rng.standard_cauchy((d, m))
        self.b = rng.uniform(0, w, m)

    def _project(self, x):
        return (x @ self.a + self.b) / self.w

    def codes(self, x):
        return np.floor(self._project(x)).astype(np.int32)

    def alternatives(self, x, n_alt):
        y = self._project(x)
        base = np.floor(y)
        r = (y - base) * self.w
        steps = np.arange(1, n_alt // 2 + 2)
        up, down = (steps * self.w - r[..., None]) ** 2, (r[..., None] + (steps - 1) * self.w) ** 2
        score = np.concatenate([up, down], axis=-1)
        delta = np.broadcast_to(np.concatenate([steps, -steps]), score.shape)
        order = np.argsort(score, axis=-1, kind="stable")[..., :n_alt]
        return (base[..., None] + np.take_along_axis(delta, order, -1)).astype(np.int32), np.take_along_axis(score, order, -1)

    def collision_prob(self, tau):
        return (theory.rp_collision_prob if self.p == 2 else theory.cauchy_collision_prob)(tau, self.w)


class CrossPolytope(Family):
    """Nearest signed axis after a random rotation: 2 * axis + (1 if negative).

    `hadamard` rotates by three rounds of sign flips and a Walsh-Hadamard transform on 2^k padded
    coordinates; `cp_dim` keeps only that many coordinates, which makes fewer symbols and fewer ties.
    """

    metric = "angular"

    def __init__(self, d: int, m: int, seed: int = 0, rotation: str = "gaussian", cp_dim: int | None = None):
        rng = np.random.Generator(np.random.Philox(seed))
        self.d, self.m, self.rotation = d, m, rotation
        self.size = 1 << (d - 1).bit_length() if rotation == "hadamard" else d
        self.dim = cp_dim or (self.size if rotation == "hadamard" else d)
        if rotation == "hadamard":
            self.signs = rng.choice([-1.0, 1.0], (m, 3, self.size))
        else:
            self.g = rng.standard_normal((m, d, self.dim))

    def _rotate(self, x, j):
        if self.rotation != "hadamard":
            y = x @ self.g[j]
        else:
            y = np.zeros((len(x), self.size))
            y[:, : x.shape[1]] = x
            for r in range(3):
                y = walsh_hadamard(y * self.signs[j, r]) / np.sqrt(self.size)
        y = y[:, : self.dim]
        return y / np.maximum(np.linalg.norm(y, axis=1, keepdims=True), 1e-300)

    def codes(self, x):
        out = np.empty((len(x), self.m), np.int32)
        for j in range(self.m):
            y = self._rotate(x, j)
            axis = np.abs(y).argmax(axis=1)
            out[:, j] = 2 * axis + (y[np.arange(len(x)), axis] < 0)
        return out

    def alternatives(self, x, n_alt):
        n_alt = min(n_alt, 2 * self.dim - 1)
        codes, scores = np.empty((len(x), self.m, n_alt), np.int32), np.empty((len(x), self.m, n_alt))
        for j in range(self.m):
            y = self._rotate(x, j)
            both = np.stack([y, -y], axis=-1).reshape(len(x), -1)
            gap = (both.max(axis=1, keepdims=True) - both) ** 2
            order = np.argsort(gap, axis=1, kind="stable")[:, 1 : n_alt + 1]
            codes[:, j], scores[:, j] = order, np.take_along_axis(gap, order, 1)
        return codes, scores

    def collision_prob(self, tau):
        return theory.cp_collision_prob(tau, self.dim)

    def rotation_matrix(self, j: int) -> np.ndarray:
        """[d, dim] of function j, without the division by the norm, which moves no largest coordinate."""
        if self.rotation != "hadamard":
            return self.g[j]
        y = np.eye(self.d, self.size)
        for r in range(3):
            y = walsh_hadamard(y * self.signs[j, r]) / np.sqrt(self.size)
        return y[:, : self.dim]


def walsh_hadamard(x: np.ndarray) -> np.ndarray:
    n, size = x.shape
    step = 1
    while step < size:
        y = x.reshape(n, -1, 2, step)
        x = np.stack([y[:, :, 0] + y[:, :, 1], y[:, :, 0] - y[:, :, 1]], axis=2).reshape(n, size)
        step *= 2
    return x


class Hyperplane(Family):
    metric = "angular"

    def __init__(self, d: int, m: int, seed: int = 0):
        self.d, self.m, self.a = d, m, np.random.Generator(np.random.Philox(seed)).standard_normal((d, m))

    def codes(self, x):
        return (x @ self.a >= 0).astype(np.int32)

    def alternatives(self, x, n_alt):
        y = x @ self.a
        return (1 - (y >= 0))[..., None].astype(np.int32), (y**2)[..., None]

    def collision_prob(self, tau):
        return theory.hyperplane_collision_prob(tau)


class BitSampling(Family):
    metric = "hamming"

    def __init__(self, d: int, m: int, seed: int = 0):
        self.d, self.m, self.at = d, m, np.random.Generator(np.random.Philox(seed)).integers(0, d, m)

    def codes(self, x):
        return x[:, self.at].astype(np.int32)

    def alternatives(self, x, n_alt):
        c = self.codes(x)
        return (1 - c)[..., None], np.ones((*c.shape, 1))

    def collision_prob(self, tau):
        return 1 - tau / self.d


#: A Mersenne prime: products of two smaller numbers fit 64 bits in any engine.
PRIME = (1 << 31) - 1


class MinHash(Family):
    """Least of (a x + b) mod PRIME over a set of integers in [0, PRIME), for m pairs (a, b); an empty set has PRIME.
    The integers are to be spread, as hashes are: of numbers in a row the least ones depend on each other.

    Alternatives of a position are its next least values, scored by how far they are behind the least.
    """

    metric = "jaccard"

    def __init__(self, m: int, seed: int = 0):
        rng = np.random.Generator(np.random.Philox(seed))
        self.m, self.a, self.b = m, rng.integers(1, PRIME, m), rng.integers(0, PRIME, m)

    def points(self, col):
        return Sets.of(col)

    def _hashes(self, s):
        return (np.asarray(s, np.int64)[:, None] * self.a + self.b) % PRIME

    def codes(self, x):
        out = np.full((len(x), self.m), PRIME, np.int32)
        for i in range(len(x)):
            if len(x[i]):
                out[i] = self._hashes(x[i]).min(axis=0)
        return out

    def alternatives(self, x, n_alt):
        codes, scores = np.full((len(x), self.m, n_alt), PRIME, np.int32), np.full((len(x), self.m, n_alt), np.inf)
        for i in range(len(x)):
            h = np.sort(self._hashes(x[i]), axis=0)[: n_alt + 1]
            if len(h) > 1:
                codes[i, :, : len(h) - 1], scores[i, :, : len(h) - 1] = h[1:].T, ((h[1:] - h[0]) / PRIME).T
        return codes, scores

    def collision_prob(self, tau):
        return 1 - tau


def encode(data: DataFrame, family: Family, keep_vec: bool = True) -> DataFrame:
    """data(id columns..., vec) with `codes ARRAY<INT>`; the family travels with the task, Arrow in and out."""
    cols = [f for f in data.schema.fields if keep_vec or f.name != "vec"]
    names = [f.name for f in cols]

    def run(batches):
        for b in batches:
            if b.num_rows:
                c = family.codes(family.points(b.column("vec")))
                flat = pa.array(np.ascontiguousarray(c).ravel(), pa.int32())
                codes = pa.ListArray.from_arrays(pa.array(np.arange(len(c) + 1) * family.m, pa.int32()), flat)
                yield pa.RecordBatch.from_arrays([*[b.column(n) for n in names], codes], names=[*names, "codes"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in cols) + ", codes array<int>"
    return data.mapInArrow(run, schema)


def valid_vectors(data: DataFrame, d: int, unit: bool = False) -> tuple[DataFrame, DataFrame]:
    """(usable, rejected): rejected rows have a null vector, a wrong size or, for unit, length 0."""
    from ringann.functions.vectors import norm

    good = F.col("vec").isNotNull() & (F.size("vec") == d) & ~F.exists("vec", lambda x: x.isNull() | F.isnan(x))
    if unit:
        good = good & (norm(F.col("vec")) > 0)
    good = F.coalesce(good, F.lit(False))
    return data.where(good), data.where(~good)


def usable(df: DataFrame, family: Family) -> DataFrame:
    """Rows whose vec a family can take: no nulls or NaN in it, of its length, and for angles not zero."""
    if family.d is None:
        return df.where(F.col("vec").isNotNull() & ~F.exists("vec", lambda x: x.isNull()))
    return valid_vectors(df, family.d, family.metric == "angular")[0]


def collision_profile(pairs: DataFrame, width: float) -> DataFrame:
    """pairs(dist, a, b): share of equal positions by distance bin."""
    from ringann.functions.runs import equal_positions

    share = equal_positions(F.col("a"), F.col("b")) / F.size("a")
    return pairs.groupBy(F.floor(F.col("dist") / width).cast("long").alias("bin")).agg(F.avg(share).alias("share"), F.count("*").alias("pairs"))
