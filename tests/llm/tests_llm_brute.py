"""Plain renderings of definitions, for comparison."""

import re

import xxhash


def brute_print(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if not words:
        return 0
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    values = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(v >> b & 1 for v in values) > len(values))


def roots(n, linked):
    """Least index of the component of each of ``n`` things under a symmetric test."""
    label = list(range(n))

    def find(i):
        while label[i] != i:
            i = label[i]
        return i

    for i in range(n):
        for j in range(i):
            if linked(i, j):
                a, b = find(i), find(j)
                label[max(a, b)] = min(a, b)
    return [find(i) for i in range(n)]


def brute_components(points, radius):
    return roots(len(points), lambda i, j: (points[i] ^ points[j]).bit_count() <= radius)


def similar_components(rows, words=5, least=0.8):
    """The smallest id that links of similarity ``least`` reach, by id; ``rows`` (id, text) in the order of ids."""
    sets = []
    for _, text in rows:
        parts = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
        sets.append({tuple(parts[i : i + words]) for i in range(max(1, len(parts) - words + 1))} if parts else set())

    def alike(i, j):
        a, b = sets[i], sets[j]
        if not a or not b:
            return not a and not b
        both = len(a & b)
        return both >= least * (len(a) + len(b) - both) - 1e-9

    return {doc: rows[root][0] for (doc, _), root in zip(rows, roots(len(rows), alike))}
