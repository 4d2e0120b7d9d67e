"""Plain definitions of what the operators must return."""

import hashlib
import math
import re
from collections import Counter
from fractions import Fraction
from math import log10
from zlib import crc32

import numpy as np
import regex


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")


def spaced(t):
    return re.findall("[^\x20\x09-\x0D]+", lower(t))


def alnum(t):
    return re.findall("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", lower(t))


def shingles(t, k=5):
    w = spaced(t)
    return {tuple(w)} if 0 < len(w) < k else {tuple(w[i : i + k]) for i in range(len(w) - k + 1)}


def deleted_lines(docs, least=120):
    """Lines that go: every window (from a line that is not blank, as many lines as reach ``least`` characters) that has an earlier
    copy is laid over the first one, and the match grows while lines are equal, not beyond what its neighbour windows decide."""
    lines = {d: (t or "").split("\n") for d, t in docs}
    first, windows = {}, {}
    for d in sorted(lines):
        ls, windows[d] = lines[d], []
        for s, x in enumerate(ls):
            e, size = s, len(x)
            while x and size < least and e + 1 < len(ls):
                e += 1
                size += len(ls[e])
            if x and size >= least:
                first.setdefault(tuple(ls[s : e + 1]), (d, s))
                windows[d].append((s, e))
    out = {}
    for d, ws in windows.items():
        ls, gone = lines[d], set()
        for k, (s, e) in enumerate(ws):
            d0, s0 = first[tuple(ls[s : e + 1])]
            if (d0, s0) == (d, s):
                continue
            other, lo, hi = lines[d0], s, e
            most = ws[k + 1][1] if k + 1 < len(ws) else len(ls) - 1
            while hi < most and hi + 1 - s + s0 < len(other) and ls[hi + 1] == other[hi + 1 - s + s0]:
                hi += 1
            while lo > 0 and not ls[lo - 1] and lo - 1 - s + s0 >= 0 and ls[lo - 1] == other[lo - 1 - s + s0]:
                lo -= 1
            gone |= set(range(lo, hi + 1))
        out[d] = gone
    return out


def hypervectors(texts, dim, vector):
    """Bundles by their definition: for every three folded letters with one in the middle, the product of rotated vectors."""
    out = []
    for t in texts:
        folded = [0]
        for c in [*(t or "").lower(), "\n"]:
            p = ord(c) if c.isalpha() else 0
            if p or folded[-1]:
                folded.append(p)
        total = np.zeros(dim)
        for a, b, c in zip(folded, folded[1:], folded[2:]):
            if b:
                total += np.roll(vector(a), 2) * np.roll(vector(b), 1) * vector(c)
        out.append(total)
    return out


def statistics(t):
    """The numbers that the rules of the quality classifier look at."""
    t = t or ""
    words, lines = [w for w in regex.split(r"\s+", t) if w], [x for x in t.split("\n") if x.strip(" ")]
    n, nw, nl = max(len(t), 1), max(len(words), 1), max(len(lines), 1)
    rate = lambda p: len(regex.findall(p, t)) / n
    return {
        "log_chars": math.log1p(len(t)), "log_words": math.log1p(len(words)), "word_length": len(t) / nw, "longest_word": math.log1p(max(map(len, words), default=0)),
        "distinct_words": len(set(words)) / nw, "distinct_lines": len(set(lines)) / nl, "line_length": math.log1p(n / nl), "letters": rate(r"\p{L}"), "capitals": rate(r"\p{Lu}"),
        "digits": rate("[0-9]"), "symbols": rate(r"[#$%&*^~=+_<>{}\[\]@/\\|]"), "bars": rate(r"\|"), "shouts": rate("!"), "stops": rate("[.?]"), "commas": rate(","),
    }


def rule_score(model, t):
    x, total = statistics(t), model.intercept
    for rule, weight in model.rules:
        if all((x[name] > cut) if more else (x[name] <= cut) for name, more, cut in rule):
            total += weight
    return 1 / (1 + math.exp(-total))


def schedule(blocks, weights):
    """Slot by slot: of the blocks that the ideal course has begun, the one that it ends first. The ideal course gives every
    source with blocks left its share of each slot, in exact fractions."""
    done, out, slot = dict.fromkeys(blocks, 0), {k: [] for k in blocks}, 0
    release, due = {k: [] for k in blocks}, {k: [] for k in blocks}
    given, now = dict.fromkeys(blocks, Fraction(0)), Fraction(0)
    left = {k for k, n in blocks.items() if n}
    while left:
        total = sum(Fraction(weights[k]) for k in left)
        end = min((blocks[k] - given[k]) / Fraction(weights[k]) * total for k in left)
        for k in left:
            rate = Fraction(weights[k]) / total
            reach = given[k] + rate * end
            for j in range(len(release[k]), blocks[k]):
                if j < reach:
                    release[k].append(math.floor(now + (j - given[k]) / rate))
            for j in range(len(due[k]), blocks[k]):
                if j + 1 <= reach:
                    due[k].append(math.ceil(now + (j + 1 - given[k]) / rate))
            given[k] = reach
        now += end
        left = {k for k in left if given[k] < blocks[k]}
    for slot in range(sum(blocks.values())):
        can = [(due[k][done[k]], k) for k in blocks if done[k] < blocks[k] and release[k][done[k]] <= slot]
        last, k = min(can)
        assert last >= slot + 1
        out[k].append(slot)
        done[k] += 1
    return out


def components(ids, links):
    parent = {i: i for i in ids}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def near(docs, percent=75):
    sets = {i: shingles(t) for i, t in docs}
    ids = list(sets)
    links = [(a, b) for k, a in enumerate(ids) for b in ids[:k] if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    comp = components(ids, links)
    return {i: (len(sets[i]), comp[i], comp[i] == i) for i in ids}


def contaminated(docs, bench, window=13):
    grams = {}
    for item, t in bench:
        w = alnum(t)
        n = min(len(w), window)
        for i in range(len(w) - n + 1) if w else ():
            grams.setdefault(tuple(w[i : i + n]), set()).add(str(item))
    sizes = {len(g) for g in grams}
    out = {}
    for d, t in docs:
        w = alnum(t)
        hit, items = set(), set()
        for n in sizes:
            for i in range(len(w) - n + 1):
                found = grams.get(tuple(w[i : i + n]))
                if found:
                    hit |= set(range(i, i + n))
                    items |= found
        sha = hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()
        out[d] = (len(w), len(hit), len(items), sha, bool(hit) and 20 * len(hit) >= len(w))
    return out


def repeats(docs, length=100):
    seen, out = set(), {}
    for d, t in sorted(docs, key=lambda x: x[0]):
        b = (t or "").encode()
        cover = [0] * (len(b) + 1)
        for s in range(len(b) - length + 1):
            w = b[s : s + length]
            if w in seen:
                cover[s] += 1
                cover[s + length] -= 1
            seen.add(w)
        kept, n, spans, run, before = bytearray(), 0, 0, 0, False
        for i, c in enumerate(b):
            run += cover[i]
            if run:
                n += 1
                spans += not before
            else:
                kept.append(c)
            before = bool(run)
        out[d] = (len(b), n, spans, hashlib.sha256(bytes(kept)).hexdigest())
    return out


def held(i, modulus, rest):
    return crc32(str(i).encode()) % modulus == rest


def base_scores(docs):
    held = {i: crc32(str(i).encode()) % 7 == 2 for i, _ in docs}
    toks = {i: [*spaced(t), None] for i, t in docs}
    c = Counter(w for i, ws in toks.items() if not held[i] for w in ws)
    n, v = sum(c.values()), len(c)
    return {i: (held[i], len(ws), sum(c[w] > 0 for w in ws), n, sum(log10((c[w] + 1) / (n + v + 1)) for w in ws)) for i, ws in toks.items()}
