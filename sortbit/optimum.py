"""Row orders of tiny tables by search: the Hamming path problem and a tour heuristic, as oracles for the sorts."""

from __future__ import annotations

from itertools import permutations


def distance(a: str, b: str) -> int:
    return sum(x != y for x, y in zip(a, b, strict=True))


def path_cost(rows: list[str]) -> int:
    return sum(distance(a, b) for a, b in zip(rows, rows[1:], strict=False))


def optimal_order(rows: list[str]) -> list[str]:
    """A cheapest order of at most 9 rows."""
    if len(rows) > 9:
        raise ValueError("brute force ends at 9 rows")
    return list(min(permutations(rows), key=lambda p: path_cost(list(p)))) if rows else []


def metric_tour_order(rows: list[str]) -> list[str]:
    """Preorder of a least spanning tree, from the first row: a closed tour of at most twice the least length."""
    if not rows:
        return []
    n = len(rows)
    parent, best, done = [0] * n, [distance(rows[0], r) for r in rows], {0}
    children: dict[int, list[int]] = {i: [] for i in range(n)}
    while len(done) < n:
        i = min((i for i in range(n) if i not in done), key=lambda i: (best[i], i))
        children[parent[i]].append(i)
        done.add(i)
        for j in range(n):
            if j not in done and (d := distance(rows[i], rows[j])) < best[j]:
                best[j], parent[j] = d, i
    out, stack = [], [0]
    while stack:
        i = stack.pop()
        out.append(rows[i])
        stack += reversed(children[i])
    return out


def edge_rows(n_vertices: int, edges: list[tuple[int, int]]) -> list[str]:
    """A graph's edges as bit rows with ones at their ends: neighbours that share an end differ in two bits, others in four."""
    return ["".join("1" if v in e else "0" for v in range(n_vertices)) for e in edges]
