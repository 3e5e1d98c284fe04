"""Brute-force versions that several test modules use."""


def brute_components(rows, n, percent):
    sets = []
    for i, t in rows:
        w = (t or "").encode().lower().split()
        sets.append((i, {tuple(w[j : j + n]) for j in range(max(1, len(w) - n + 1))} if w else set()))
    label = {i: i for i, _ in sets}
    changed = True
    links = [(a, b) for x, (a, s) in enumerate(sets) for b, t in sets[x + 1 :] if s and t and 100 * len(s & t) >= percent * len(s | t)]
    while changed:
        changed = False
        for a, b in links:
            m = min(label[a], label[b])
            if label[a] != m or label[b] != m:
                label[a] = label[b] = m
                changed = True
    return sorted((i, len(s), label[i]) for i, s in sets)
