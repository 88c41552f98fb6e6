"""Plain versions of the operators, for small inputs."""

import re
from itertools import combinations

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def words(text):
    return WORD.findall(text or "")


def lower(text):
    return re.sub("[A-Z]", lambda m: m.group().lower(), text or "")


def shingles(text):
    w = words(lower(text))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def near_components(docs, percent=85):
    """docs: {id: text} -> {id: component}."""
    root = {i: i for i in docs}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    sets = {i: shingles(t) for i, t in docs.items()}
    for a, b in combinations(sorted(docs), 2):
        x, y = sets[a], sets[b]
        if x and y and 100 * len(x & y) >= percent * len(x | y):
            p, q = find(a), find(b)
            root[max(p, q)] = min(p, q)
    return {i: find(i) for i in docs}


def one_edit(a, b):
    if len(a) == len(b):
        return sum(x != y for x, y in zip(a, b)) <= 1
    if abs(len(a) - len(b)) != 1:
        return False
    s, t = sorted((a, b), key=len)
    return any(t[:i] + t[i + 1 :] == s for i in range(len(t)))


def kept_lines(docs, least=8):
    """docs: {id: text} -> {id: text with its kept lines}."""
    seen, out = [], {}
    for i in sorted(docs):
        keep = []
        for line in docs[i].split("\n"):
            w = words(line.lower())
            if not w:
                keep.append(line)
                continue
            same = any(w == v for v in seen)
            near = any(len(w) >= least and len(v) >= least and one_edit(w, v) for v in seen)
            if not same:
                seen.append(w)
            if not (same or near):
                keep.append(line)
        out[i] = "\n".join(keep)
    return out
