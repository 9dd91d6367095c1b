"""Ring multi-probe: perturbed query strings in ascending score, searched only where they can differ."""

from __future__ import annotations

import heapq

import numpy as np

from ringann.operators import rotation

MAX_GAP = 2


def perturbations(scores: np.ndarray, n_probes: int, max_gap: int = MAX_GAP) -> list[tuple[tuple[tuple[int, int], ...], float]]:
    """[(((position, alternative), ...), score)], the empty one first; scores[m, n_alt] ascend along alternatives.

    A probe's successors are its last change moved to the next alternative, and one more change at a distance of
    up to max_gap behind its last. Each vector has one predecessor with a lower or equal score, so each appears
    once and in order. Changes beyond the last position or alternative do not exist.
    """
    m, n_alt = scores.shape
    out = [((), 0.0)]
    heap = [(float(scores[i, 0]), ((i, 0),)) for i in range(m)]
    heapq.heapify(heap)
    while heap and len(out) < n_probes:
        score, delta = heapq.heappop(heap)
        out.append((delta, score))
        pos, alt = delta[-1]
        if alt + 1 < n_alt:
            heapq.heappush(heap, (score - float(scores[pos, alt]) + float(scores[pos, alt + 1]), (*delta[:-1], (pos, alt + 1))))
        for gap in range(1, max_gap + 1):
            if pos + gap < m:
                heapq.heappush(heap, (score + float(scores[pos + gap, 0]), (*delta, (pos + gap, 0))))
    return out


def probe_table(queries, family, n_probes: int, n_alt: int = 4, max_gap: int = MAX_GAP):
    """(qid, probe_no, score, changes ARRAY<STRUCT<pos, code>>): the probes of every query, computed where queries are read."""
    import pyarrow as pa
    from pyspark.sql import functions as F

    from ringann.operators.families import usable

    def run(batches):
        for b in batches:
            if not b.num_rows:
                continue
            codes, scores = family.alternatives(family.points(b.column("vec")), n_alt)
            for i, qid in enumerate(b.column("qid").to_pylist()):
                found = perturbations(scores[i], n_probes, max_gap)
                changes = [[{"pos": int(p), "code": int(codes[i, p, a])} for p, a in delta] for delta, _ in found]
                yield pa.RecordBatch.from_arrays([pa.array([qid] * len(found), pa.int64()), pa.array(range(len(found)), pa.int32()), pa.array([s for _, s in found], pa.float64()), pa.array(changes, pa.list_(pa.struct([("pos", pa.int32()), ("code", pa.int32())])))], names=["qid", "probe_no", "score", "changes"])

    kind = "array<double>" if family.d is not None else "array<long>"
    rows = usable(queries, family).select("qid", F.col("vec").cast(kind).alias("vec"))
    return rows.mapInArrow(run, "qid long, probe_no int, score double, changes array<struct<pos:int,code:int>>")


def alternative_table(data, family, n_alt: int):
    """(obj_id, pos, place, code, score): every position's alternatives, the best first."""
    import pyarrow as pa
    from pyspark.sql import functions as F

    from ringann.operators.families import usable

    def run(batches):
        for b in batches:
            if b.num_rows:
                codes, scores = family.alternatives(family.points(b.column("vec")), n_alt)
                n, m, k = codes.shape
                line = np.arange(n * m * k)
                cols = [np.repeat(b.column("obj_id").to_numpy(), m * k), (line // k % m).astype(np.int32), (line % k).astype(np.int32), codes.ravel().astype(np.int32), scores.ravel()]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=["obj_id", "pos", "place", "code", "score"])

    kind = "array<double>" if family.d is not None else "array<long>"
    rows = usable(data, family).select("obj_id", F.col("vec").cast(kind).alias("vec"))
    return rows.mapInArrow(run, "obj_id long, pos int, place int, code int, score double")


def probe_grid(m: int) -> list[int]:
    return [1, m + 1, 2 * m + 1, 4 * m + 1, 8 * m + 1]


def affected(bound: np.ndarray, first: int) -> list[int]:
    """Rotations whose search looked at position `first`, its first mismatch included; in order, ending there."""
    return _reached(bound[:, 2:].max(axis=1), first)


def _reached(reach: np.ndarray, first: int) -> list[int]:
    m = len(reach)
    return [i for i in ((first - d) % m for d in range(m - 1, -1, -1)) if (first - i) % m <= reach[i]]


def strings(q: np.ndarray, alt_codes: np.ndarray, scores: np.ndarray, n_probes: int, max_gap: int = MAX_GAP) -> list[np.ndarray]:
    """The query's code string and those of its probes."""
    out = []
    for delta, _ in perturbations(scores, n_probes, max_gap):
        p = q.copy()
        for pos, alt in delta:
            p[pos] = alt_codes[pos, alt]
        out.append(p)
    return out


def search_rows(shard: rotation.Shard, q: np.ndarray, alt_codes: np.ndarray, scores: np.ndarray, k: int, n_probes: int, max_gap: int = MAX_GAP, skip: bool = True, ties: bool = False) -> tuple[np.ndarray, np.ndarray, int]:
    """(rows, longest prefixes with the query or a probe, rotations searched again). skip=False searches every rotation of every probe.

    A probe differs from the one without its first change in that position only, so only those rotations are searched
    again whose window in the search of that one reaches it; windows that a later change has stretched round to
    the first are among them.
    """
    heap: list = []
    base = rotation.bounds(shard, q)
    rotation.push_heads(shard, heap, base, range(shard.m), q, 0)
    again = 0
    reaches = {(): base[:, 2:].max(axis=1)}
    for number, (delta, _) in enumerate(perturbations(scores, n_probes, max_gap)[1:], 1):
        p = q.copy()
        for pos, alt in delta:
            p[pos] = alt_codes[pos, alt]
        reach = reaches.get(delta[1:])  # none where equal scores put a probe before its part
        rots = _reached(reach, delta[0][0]) if skip and reach is not None else list(range(shard.m))
        again += len(rots)
        found = np.zeros_like(base)
        before = None
        for i in rots:
            rq = np.concatenate([p[i:], p[:i]])
            lo, hi = 0, shard.n
            if before is not None and (before + 1) % shard.m == i and found[before, 2] and found[before, 3]:
                lo, hi = int(shard.link[before, found[before, 0]]) + 1, int(shard.link[before, found[before, 1]])
            up = rotation._bisect(shard, i, rq, lo, hi)
            found[i] = (
                up - 1, up,
                rotation._lcp(shard.rotated(shard.order[i, up - 1], i), rq) if up else 0,
                rotation._lcp(shard.rotated(shard.order[i, up], i), rq) if up < shard.n else 0,
            )
            before = i
        reaches[delta] = np.zeros(shard.m, np.int64) if reach is None else reach.copy()
        reaches[delta][rots] = found[rots, 2:].max(axis=1)
        rotation.push_heads(shard, heap, found, rots, p, number)
    return *rotation._merge(shard, heap, min(k, shard.n), ties), again


def search(shard: rotation.Shard, q: np.ndarray, alt_codes: np.ndarray, scores: np.ndarray, k: int, n_probes: int, max_gap: int = MAX_GAP, skip: bool = True, ties: bool = False) -> tuple[dict[int, int], int]:
    """search_rows as ({row: longest prefix}, rotations searched again)."""
    rows, lens, again = search_rows(shard, q, alt_codes, scores, k, n_probes, max_gap, skip, ties)
    return dict(zip(rows.tolist(), lens.tolist())), again
