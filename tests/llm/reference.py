"""Plain Python versions of the contracts, for small tables."""

import hashlib
import math
import re
from collections import Counter, defaultdict

SPACE = "\x20\t\n\x0b\x0c\r"
KINDS = ["email", "ip", "card", "phone"]


def low(text):
    return (text or "").encode().lower().decode()


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


def luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        x = int(c)
        total += x if i % 2 == 0 else 2 * x - 9 * (x > 4)
    return total % 10 == 0


def base_spans(text):
    text, out = text or "", []
    digits = lambda s: re.sub("[^0-9]", "", s)
    for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text):
        out.append((m.start(), 0, m.end()))
    for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text):
        if all(int(x) <= 255 for x in m[0].split(".")):
            out.append((m.start(), 1, m.end()))
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        if 12 <= len(digits(m[0])) <= 19 and luhn(digits(m[0])):
            out.append((m.start(), 2, m.end()))
    for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text):
        if 9 <= len(digits(m[0])) <= 15:
            out.append((m.start(), 3, m.end()))
    return sorted(out)


def exact_groups(rows):
    groups = defaultdict(list)
    for i, text in rows:
        groups[low(text)].append(i)
    out = Counter()
    for i, text in rows:
        ids = groups[low(text)]
        stays = max([x for x in ids if x is not None], default=None)
        out[i, stays, len(ids), stays == i, sha(low(text))] += 1
    return out


def kept_lines(rows):
    key = lambda line: low(line.strip(SPACE))
    holders = defaultdict(set)
    for i, text in rows:
        for line in (text or "").split("\n"):
            if len(key(line)) >= 40:
                holders[key(line)].add(-math.inf if i is None else i)
    stays = {k: max(v) for k, v in holders.items() if len(v) >= 5}
    out = []
    for i, text in rows:
        lines = (text or "").split("\n")
        here = -math.inf if i is None else i
        out.append((i, len(lines), [x for x in lines if stays.get(key(x), here) == here]))
    return out


def shingle_set(text):
    words = low(text).encode().split()
    if len(words) < 5:
        return frozenset([tuple(words)]) if words else frozenset()
    return frozenset(tuple(words[k : k + 5]) for k in range(len(words) - 4))


def components(sets):
    """Least identifier reachable over links, from all pairs."""
    ids = sorted(sets)
    label = {i: i for i in ids}

    def find(x):
        while label[x] != x:
            x = label[x]
        return x

    for n, i in enumerate(ids):
        for j in ids[:n]:
            a, b = sets[i], sets[j]
            if a and b and 100 * len(a & b) >= 75 * len(a | b):
                x, y = find(i), find(j)
                label[max(x, y)] = min(x, y)
    return {i: find(i) for i in ids}
