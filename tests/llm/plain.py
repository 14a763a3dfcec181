"""Plain versions that tests hold operators against: no Spark, no hashing, all pairs."""

import re
import zlib
from collections import Counter
from math import comb, log

from flipmine.llm import risk_rules

WORD = re.compile(r"[^\x20\x09-\x0d]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words(text):
    return WORD.findall((text or "").translate(LOWER))


def measures(text):
    """(base_failed, shares in the order of the rules)."""
    t = text or ""
    w = WORD.findall(t)
    grams = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
    counts = Counter(grams)
    covered = {k + j for k, g in enumerate(grams) if counts[g] > 1 for j in range(3)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    chars, part = sum(map(len, w)), lambda a, b: a / b if b else 0.0
    shares = (part(len(re.findall(r"[#*$%&|<>]", t)), chars), part(t.count("!"), chars), part(len(re.findall("[A-Z]", t)), chars), part(len(lines) - len(set(lines)), len(lines)), part(len(covered), len(w)))
    return len(w) < 50 or 100 * len(covered) > 50 * len(w), shares


def kept(rows, labels):
    """doc_id to verdict of (doc_id, text, lang) rows with distinct ids; ``labels`` has the quality of some."""
    steps, failed = {}, {}
    for i, text, _ in rows:
        failed[i], shares = measures(text)
        steps[i] = tuple(sum(x >= g for g in risk_rules.GRID) for x in shares)
    guide = lambda i: zlib.crc32(f"guide{i}".encode()) % risk_rules.GUIDES == 0
    strata = {}
    for i, _, lang in rows:
        if i in labels:
            strata.setdefault(lang or "", []).append(i)
    good = {s: [i for i in ids if labels[i] == 1 and not guide(i)] for s, ids in strata.items()}
    tested = [s for s in strata if len(good[s]) * log(1 - risk_rules.RISK) <= log(risk_rules.DOUBT)]
    cuts = {}
    for s in tested:
        bad = [i for i in strata[s] if labels[i] == 0 and not failed[i]]
        guides = [i for i in strata[s] if labels[i] == 1 and guide(i)]
        reach = lambda ids, rule, cut: sum(steps[i][rule] >= cut for i in ids)
        order = []
        for rule in range(len(risk_rules.SHARES)):
            before, worth = 0, float("inf")
            for cut in range(len(risk_rules.GRID), 0, -1):
                n = reach(bad, rule, cut)
                if n > before:
                    worth = min(worth, n / (reach(guides, rule, cut) + 1))
                    order.append((-worth, rule, -cut))
                before = n
        order = [(rule, -cut) for _, rule, cut in sorted(order)]
        first = lambda i, order: next((p for p, (rule, cut) in enumerate(order) if steps[i][rule] >= cut), None)
        useful = {first(i, order) for i in bad}
        order = [x for p, x in enumerate(order) if p in useful]
        at = Counter(first(i, order) for i in good[s])
        k = 0
        for p, (rule, cut) in enumerate(order):
            k += at[p]
            n, r = len(good[s]), risk_rules.RISK
            tail = 1.0 if k > n * r else sum(comb(n, j) * r**j * (1 - r) ** (n - j) for j in range(k + 1))
            if tail > risk_rules.DOUBT / len(tested):
                break
            cuts[s, rule] = min(cut, cuts.get((s, rule), 99))
    return {i: not failed[i] and not any(steps[i][rule] >= cuts.get((lang or "", rule), 99) for rule in range(len(risk_rules.SHARES))) for i, _, lang in rows}


def components(texts, size, percent):
    """id to the smallest id that links reach, by all pairs of ``texts`` (id to text)."""
    sets = {i: frozenset(tuple(w[k : k + size]) for k in range(max(1, len(w) - size + 1))) if (w := words(t)) else frozenset() for i, t in texts.items()}
    up = {i: i for i in texts}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(texts)
    for n, i in enumerate(ids):
        for j in ids[n + 1 :]:
            a, b = sets[i], sets[j]
            if a and b and 100 * len(a & b) >= percent * len(a | b):
                x, y = sorted((root(i), root(j)))
                up[y] = x
    return {i: root(i) for i in ids}


def contaminated(text, items, size=10):
    split = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOWER))
    own = f" {' '.join(split(text))} "
    return any(f" {' '.join(w[k : k + size])} " in own for item in items for w in [split(item)] for k in range(max(1, len(w) - size + 1) if w else 0))
