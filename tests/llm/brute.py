"""Plain versions of the operators over a dict of texts, for small inputs."""

from __future__ import annotations

import re
from collections import Counter, defaultdict
from math import exp, log, log2

from portsweep.llm import quality, substring_dedup

WORD = "[^\x20\x09-\x0d]+"


def measures(t):
    w = re.findall(WORD, t)
    seen, dup, hit = set(), 0, set()
    for line in t.split("\n"):
        if re.search("[^\x20\x09-\x0d]", line):
            dup += line in seen
            seen.add(line)
    at = defaultdict(list)
    for k in range(len(w) - 7):
        at[tuple(w[k : k + 8])].append(k)
    for v in at.values():
        if len(v) > 1:
            hit |= {k + j for k in v for j in range(8)}
    return len(w), sum(map(len, w)), sum(t.count(c) for c in "#*$%&|<>"), dup, len(hit)


def base_failed(t):
    m = measures(t)
    return m[0] < 20 or 100 * m[4] > 30 * m[0]


def ballot(t):
    """The votes of all rules on one text."""
    w, chars, symbols, dup, repeated = measures(t)
    lines = [x for x in (y.rstrip(" \t\n\x0b\x0c\r") for y in t.split("\n")) if x.strip(" \t\n\x0b\x0c\r")]
    ended, letters = sum(x[-1] in ".!?\"'»”)" for x in lines), sum(c not in " \t\n\x0b\x0c\r0123456789.,;:!?()[]{}\"'-_/\\+=~^`@#*$%&|<>" for c in t)
    rules = [
        (w < 20, w >= 50), (chars < 2 * w or chars > 15 * w, 3 * w <= chars <= 10 * w), (10 * symbols > w, 100 * symbols <= w),
        (10 * dup > 3 * len(lines), dup == 0 and len(lines) > 1), (5 * repeated > w, 20 * repeated <= w), (10 * letters < 7 * chars, 10 * letters >= 9 * chars), (10 * ended < len(lines), 2 * ended >= len(lines)),
    ]
    return tuple(-1 if bad else 1 if good else 0 for bad, good in rules)


def kept(texts, rounds=200):
    """Ids that a document-by-document EM over the rules' votes keeps."""
    ballots = {i: ballot(t) for i, t in texts.items()}
    start = [list(quality.START_BAD), list(quality.START_GOOD)]
    says, good = [[list(start[c]) for _ in quality.RULES] for c in (0, 1)], 0.8

    def belief(b):
        odds = log(good / (1 - good)) + sum(log(says[1][r][v + 1] / says[0][r][v + 1]) for r, v in enumerate(b))
        return 1 / (1 + exp(-max(-500, min(500, odds))))

    for _ in range(rounds):
        p = {i: belief(b) for i, b in ballots.items()}
        new = [[[20 * s for s in start[c]] for _ in quality.RULES] for c in (0, 1)]
        for i, b in ballots.items():
            for r, v in enumerate(b):
                new[0][r][v + 1] += 1 - p[i]
                new[1][r][v + 1] += p[i]
        for r in range(len(quality.RULES)):
            for c in (0, 1):
                total = sum(new[c][r])
                new[c][r] = [x / total for x in new[c][r]]
            new[0][r][0], new[1][r][2] = max(new[0][r][0], new[1][r][0]), max(new[1][r][2], new[0][r][2])
            for c in (0, 1):
                total = sum(new[c][r])
                new[c][r] = [x / total for x in new[c][r]]
        share = min(0.99, max(0.01, sum(p.values()) / len(p)))
        moved = max(abs(share - good), max(abs(new[c][r][v] - says[c][r][v]) for c in (0, 1) for r in range(len(quality.RULES)) for v in range(3)))
        says, good = new, share
        if moved < 1e-9:
            break
    return {i for i, t in texts.items() if not base_failed(t) and belief(ballots[i]) >= 0.5}


def jaccard(texts, width, num):
    """id -> (size of its set, least id linked)."""
    sets, inv = {}, defaultdict(list)
    for i, t in texts.items():
        w = re.findall(WORD, "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t))
        sets[i] = {tuple(w[k : k + width]) for k in range(max(len(w) - width + 1, 1))} if w else set()
        for g in sets[i]:
            inv[g].append(i)
    both, root = Counter(), {i: i for i in texts}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for ids in inv.values():
        both.update((min(a, b), max(a, b)) for k, a in enumerate(ids) for b in ids[:k])
    for (a, b), c in both.items():
        if 100 * c >= num * (len(sets[a]) + len(sets[b]) - c):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in texts}


def stripped(texts, rules=substring_dedup.RULES):
    """id -> (text that is left, sentences removed); texts in order of id."""

    def ok(p):
        return any(len(p) >= k and sum(map(len, p)) >= w for k, w in rules)

    at = defaultdict(list)
    for i in sorted(texts):
        parts = [(k, p.split()) for k, p in enumerate(substring_dedup.sentences(texts[i])) if p.split()]
        for a in range(len(parts)):
            for b in range(a + 1, len(parts) + 1):
                p = [w for _, w in parts[a:b]]
                if ok(p):
                    if not ok(p[:-1]) or not ok(p[1:]):
                        at[tuple(map(tuple, p))].append((i, parts[a][0], parts[b - 1][0] + 1))
                    if ok(p[:-1]) and ok(p[1:]):
                        break
    gone = defaultdict(set)
    for v in at.values():
        for i, a, b in v:
            if (i, a, b) != min(v):
                gone[i] |= set(range(a, b))
    out = {}
    for i, t in texts.items():
        left = "".join(s for k, s in enumerate(substring_dedup.sentences(t)) if k not in gone[i])
        out[i] = (left.rstrip() if gone[i] else t, len(gone[i]))
    return out


def luhn(d):
    return sum((x - 9 if x > 9 else x) for i, c in enumerate(reversed(d)) for x in [int(c) * (2 if i % 2 else 1)]) % 10 == 0


def personal(t):
    """Base spans (kind, start, end) of one text, by kind and start."""
    out = [(0, m.start(), m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [(1, m.start(), m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[^0-9]", "", m[0])
        out += [(2, m.start(), m.end())] if 16 <= len(d) <= 19 and luhn(d) else []
    out += [(3, m.start(), m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 8 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
    return sorted(out)


def disclosed(texts, alpha=0.8):
    """id -> all spans (kind, start, end): base ones and terms whose pointwise mutual information with an entity is high."""
    import regex

    term = regex.compile(r"[\p{L}\p{N}]+")
    base, entities, words = {}, {}, {}
    for i, t in texts.items():
        base[i], entities[i] = personal(t), set()
        words[i] = [(m[0].lower(), m.start(), m.end()) for m in term.finditer(t)]
        for k, a, b in base[i]:
            m = t[a:b].lower()
            entities[i].add((k, m if k < 2 else re.sub("[^0-9]", "", m)))
            if k == 0:
                entities[i] |= {("account", m.split("@")[0]), ("domain", m.rsplit("@", 1)[1])}
            if k == 1:
                entities[i].add(("network", ".".join(m.split(".")[:3])))
    n, held, told = len(texts), defaultdict(set), Counter()
    for i in texts:
        for e in entities[i]:
            held[e].add(i)
        told.update({w for w, _, _ in words[i]})
    out = {}
    for i in texts:
        bad = set()
        for e in entities[i]:
            docs = held[e]
            if len(docs) == n:
                continue
            both = Counter(w for j in docs for w in {x for x, _, _ in words[j]})
            bad |= {w for w, _, _ in words[i] if log2(n * both[w] / (len(docs) * told[w])) >= alpha * log2(n / len(docs))}
        terms = [(5 if regex.fullmatch(r"\p{N}+", texts[i][a:b]) else 4, a, b) for w, a, b in words[i] if w in bad and not any(x < b and a < y for _, x, y in base[i])]
        out[i] = sorted(base[i] + terms)
    return out


def sanitised(texts):
    marks, out = ("[EMAIL]", "[IP]", "[CARD]", "[PHONE]", "[TERM]", "[NUMBER]"), {}
    for i, spans in disclosed(texts).items():
        at, text = 0, ""
        for a, k, b in sorted((a, k, b) for k, a, b in spans):
            if a >= at:
                text += texts[i][at:a] + marks[k]
            at = max(at, b)
        out[i] = text + texts[i][at:]
    return out
