"""Plain versions of the corpus operators, for small inputs."""

import collections
import hashlib
import re

LAST = 2**63 - 1
WORD = re.compile(rb"[^\x20\x09-\x0D]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def ident(x):
    return LAST if x is None else x


def repeats(rows, cut, length):
    """[(doc, tokens, removed flags)] for token lists given by cut(text)."""
    tokens = [(ident(d), cut(t)) for d, t in rows]
    least = {}
    for d, w in tokens:
        for i in range(len(w) - length + 1):
            key = tuple(w[i : i + length])
            least[key] = min(d, least.get(key, d))
    out = []
    for d, w in tokens:
        gone = [False] * len(w)
        for i in range(len(w) - length + 1):
            if least[tuple(w[i : i + length])] < d:
                gone[i : i + length] = [True] * length
        out.append((d, w, gone))
    return out


def repeated_words(rows):
    return sorted((d, len(w), sum(g), hashlib.sha256(b" ".join(x for x, y in zip(w, g, strict=True) if not y)).hexdigest()) for d, w, g in repeats(rows, lambda t: WORD.findall((t or "").encode()), 13))


def repeated_bytes(rows):
    out = []
    for d, b, g in repeats(rows, lambda t: (t or "").encode(), 50):
        kept = bytes(x for x, y in zip(b, g, strict=True) if not y)
        out.append((d, len(b), sum(g), len(re.findall(b"\x01+", bytes(g))), hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def linked(rows, size=4, percent=85):
    sets = []
    for d, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOWER))
        sets.append((ident(d), frozenset(tuple(w[i : i + size]) for i in range(max(1, len(w) - size + 1))) if w else frozenset()))
    root = list(range(len(sets)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    index = collections.defaultdict(list)
    for i, (_, s) in enumerate(sets):
        shared = collections.Counter(j for g in s for j in index[g])
        for j, n in shared.items():
            if 100 * n >= percent * (len(s) + len(sets[j][1]) - n):
                root[find(i)] = find(j)
        for g in s:
            index[g].append(i)
    least = {}
    for i, (d, _) in enumerate(sets):
        least[find(i)] = min(d, least.get(find(i), LAST))
    return sorted((d, len(s), least[find(i)]) for i, (d, s) in enumerate(sets))


def exact(rows):
    groups = collections.defaultdict(list)
    for d, t in rows:
        groups[(t or "").translate(dict.fromkeys((32, 9, 10, 11, 12, 13)))].append((-len(t or ""), ident(d)))
    out = []
    for plain, members in groups.items():
        keep = min(members)[1]
        out += [(d, keep, len(members), d == keep, hashlib.sha256(plain.encode()).hexdigest()) for _, d in members]
    return sorted(out)
