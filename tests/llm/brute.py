"""Plain Python versions of the operators' contracts, by definition and without regard to speed."""

import hashlib
import html
import re
from collections import defaultdict
from fractions import Fraction

PATTERNS = (
    ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"),
    ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"),
    ("card", r"[0-9]([\x20-]?[0-9])+"),
    ("phone", r"\+[0-9][\x20().0-9-]+[0-9]"),
)


def luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        v = int(c) * (2 if i % 2 else 1)
        total += v - 9 if v > 9 else v
    return total % 10 == 0


def base_spans(text):
    out = []
    for k, (kind, pattern) in enumerate(PATTERNS):
        for m in re.finditer(pattern, text or ""):
            d = re.sub("[^0-9]", "", m[0])
            ok = {"email": lambda: True, "ip": lambda: all(int(x) <= 255 for x in m[0].split(".")), "card": lambda: 14 <= len(d) <= 19 and luhn(d), "phone": lambda: 10 <= len(d) <= 15}[kind]()
            if ok:
                out.append((m.start(), k, m.end(), kind))
    return sorted(out)


def pii_row(text):
    spans = base_spans(text)
    said = ",".join(f"{kind}:{a}:{b}" for a, _, b, kind in spans)
    return tuple(sum(s[3] == k for s in spans) for k, _ in PATTERNS) + (hashlib.sha256(said.encode()).hexdigest(),)


def ascii_lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def url_row(url, rules):
    at = way = ""
    if url and "://" in url:
        m = re.match(r"(?s).*?://([^/?#]*)([^?#]*)", url)
        at, way = ascii_lower(m[1]), m[2]
    best = None
    for verdict, rule in rules:
        top, slash, rest = rule.partition("/")
        if (at == top or at.endswith("." + top)) and way.startswith(slash + rest) and (best is None or len(rule) > len(best[1])):
            best = (verdict, rule)
    return at, way, best


def shingle_set(text, size):
    words = re.findall(r"[^\x20\x09-\x0D]+", ascii_lower(text))
    if not words:
        return frozenset()
    size = min(size, len(words))
    return frozenset(tuple(words[i : i + size]) for i in range(len(words) - size + 1))


def near_components(docs, size, percent):
    """doc_id -> (set size, component); docs: list of (doc_id, text)."""
    sets = {i: shingle_set(t, size) for i, t in docs}
    by = defaultdict(list)
    for i, s in sets.items():
        for x in s:
            by[x].append(i)
    parent = {i: i for i in sets}

    def root(i):
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    for i, s in sets.items():
        common = defaultdict(int)
        for x in s:
            for j in by[x]:
                if j < i:
                    common[j] += 1
        for j, n in common.items():
            if 100 * n >= percent * (len(s) + len(sets[j]) - n):
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
    return {i: (len(s), root(i)) for i, s in sets.items()}


def exact_rows(docs):
    groups = defaultdict(list)
    for i, t in docs:
        groups[ascii_lower(t)].append(i)
    return sorted((i, max(ids), len(ids), i == max(ids), hashlib.sha256(t.encode()).hexdigest()) for t, ids in groups.items() for i in ids)


def mix_targets(sizes, share=Fraction(3, 2), weights=(5, 2, 1), most=2):
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    w = {s: weights[i % 3] for i, s in enumerate(names)}
    total = share * sum(sizes.values())
    t = {s: total * w[s] / sum(w.values()) for s in names}
    while any(t[s] > most * sizes[s] for s in names):
        over = sum(max(Fraction(0), t[s] - most * sizes[s]) for s in names)
        for s in names:
            t[s] = min(t[s], Fraction(most * sizes[s]))
        free = [s for s in names if t[s] < most * sizes[s]]
        if not free:
            break
        for s in free:
            t[s] += over * w[s] / sum(w[x] for x in free)
    return t


def page_text(page):
    """Of the shape that the given pages have: blocks of what stands in <article>."""
    body = re.search(r"(?s)<article>(.*?)</article>", page or "")
    parts = re.split(r"</?(?:h1|p)>", body[1]) if body else []
    blocks = (re.sub(r"\s+", " ", html.unescape(re.sub(r"<[^>]*>", " ", x))).strip() for x in parts)
    return "\n".join(b for b in blocks if b)
