"""Plain versions of the operators, for small inputs."""

from __future__ import annotations

import re
from collections import Counter, defaultdict

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def bag(text: str | None, size: int = 5) -> Counter:
    words = WORD.findall(text or "")
    if not words:
        return Counter()
    if len(words) < size:
        return Counter([tuple(words)])
    return Counter(tuple(words[i : i + size]) for i in range(len(words) - size + 1))


def near_duplicates(rows: list[tuple[int, str | None]], threshold: float = 0.8) -> dict[int, tuple[int, int]]:
    """id -> (class, component)."""
    bags = {i: bag(t) for i, t in rows}
    classes: dict = {}
    for i in sorted(bags):
        if bags[i]:
            classes.setdefault(frozenset(bags[i].items()), i)
    of = {i: classes[frozenset(b.items())] if b else i for i, b in bags.items()}
    root = {i: i for i in bags}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    held = defaultdict(list)
    reps = sorted(set(classes.values()))
    for i in reps:
        near = Counter()
        for s, n in bags[i].items():
            for j, m in held[s]:
                near[j] += min(n, m)
            held[s].append((i, n))
        for j, both in near.items():
            if both / (sum(bags[i].values()) + sum(bags[j].values()) - both) >= threshold:
                a, b = sorted((find(i), find(j)))
                root[b] = a
    return {i: (of[i], find(of[i])) for i in bags}
