"""Slow references, written from the definitions with plain loops."""

from __future__ import annotations


def latest(rows, m):
    """rows (child, ts) -> the m latest, rows without time last, ties by child."""
    return sorted(rows, key=lambda r: (r[1] is None, -(r[1].timestamp() if r[1] else 0), r[0]))[:m]


def slice_edges(children, seed, t, caps):
    """children: list of {parent: [(child, ts)]} for each hop; edges (hop, child, parent) by latest-first."""
    frontier, out = {seed}, []
    for hop, (table, m) in enumerate(zip(children, caps, strict=True), 1):
        nxt = set()
        for p in sorted(frontier):
            near = [r for r in table.get(p, []) if r[1] is None or r[1] <= t]
            for c, _ in latest(near, m):
                out.append((hop, c, p))
                nxt.add(c)
        frontier = nxt
    return out


def average_precision(rows):
    """rows (label, score): every distinct score is a threshold."""
    total = sum(y for y, _ in rows)
    if not total:
        return None
    ap, seen, hits = 0.0, 0, 0
    for s in sorted({s for _, s in rows}, reverse=True):
        here = [y for y, q in rows if q == s]
        seen, hits = seen + len(here), hits + sum(here)
        ap += sum(here) / total * hits / seen
    return ap
