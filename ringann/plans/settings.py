"""Parameters that the registered queries and their SQL share."""

from __future__ import annotations

from ringann.operators import families

D, M, W, LAM, K, EVERY = 64, 8, 2.0, 50, 10, 50


def of_width(w: float) -> families.RandomProjection:
    return families.RandomProjection(D, M, w, seed=7)


RP = of_width(W)
HP = families.Hyperplane(D, M, seed=7)
CP = families.CrossPolytope(D, M, seed=7, rotation="hadamard", cp_dim=8)
CAUCHY = families.RandomProjection(D, M, 8.0, seed=7, p=1)
BITS = families.BitSampling(D, 16, seed=7)
MH = families.MinHash(8, seed=7)

#: Rows as an experiment measures them, for the measures that reduce such rows.
RESULTS = [
    ("ring", "m=8", 0.45, 1.21, 0.010, 1000), ("ring", "m=64", 0.62, 1.10, 0.020, 8000), ("ring", "m=256", 0.93, 1.01, 0.075, 32000),
    ("ring", "m=64", 0.60, 1.12, 0.024, 8000), ("static_concat", "K=2,L=8", 0.55, 1.15, 0.050, 6000), ("static_concat", "K=3,L=64", 0.92, 1.02, 0.200, 50000),
    ("collision_count", "m=64,l=4", 0.97, 1.00, 0.300, 9000), ("collision_count", "m=16,l=2", 0.35, 1.30, 0.060, 2000),
]

#: Settings that the reductions measure: functions and candidates of the ring, visits of the projection; recalls they are asked for.
RINGS, VISITED, LEVELS = [(2, 50), (8, 10), (8, 200)], [20, 400], [0.01, 0.05, 0.2]
