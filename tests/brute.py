"""Brute-force references: every occurrence, and the largest set of disjoint ones by earliest end."""

from itertools import product

from episodic.model import Episode


def occurrences(stream: list[tuple[str, int]], e: Episode) -> list[tuple[int, ...]]:
    """Places of each occurrence; the stream is in order."""
    found = [(i,) for i, (s, _) in enumerate(stream) if s == e.nodes[0]]
    for k, edge in enumerate(e.edges, 1):
        found = [
            (*o, i) for o, (i, (s, t)) in product(found, enumerate(stream)) if s == e.nodes[k] and edge.low < t - stream[o[-1]][1] and (edge.high is None or t - stream[o[-1]][1] <= edge.high)
        ]
    return found


def support(stream: list[tuple[str, int]], e: Episode) -> int:
    n, last = 0, -1
    for a, b in sorted(((o[0], o[-1]) for o in occurrences(stream, e)), key=lambda x: x[1]):
        if a > last:
            n, last = n + 1, b
    return n
