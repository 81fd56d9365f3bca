"""Plain versions of the contracts, in Python, for small inputs."""

import hashlib
import math
import re
from collections import defaultdict

import xxhash

ASCII_LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
DATA = "/root/testdata/sf0.01"


def sha(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()


def plain_fingerprint(text, size=3):
    words = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(ASCII_LOWER))
    if not words:
        return 0
    shingles = [" ".join(words[i:i + size]) for i in range(len(words) - size + 1)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def plain_components(ids, edges):
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x
    for a, b in edges:
        a, b = find(a), find(b)
        root[max(a, b)] = min(a, b)
    return {i: find(i) for i in ids}


def plain_contamination(docs, items):
    """doc_id -> (n_words, n_hit, n_items, sha, contaminated)"""
    split = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(ASCII_LOWER))
    owners, sizes = defaultdict(set), set()
    for item, text in items:
        w = split(text)
        for i in range(max(1, len(w) - 9) if w else 0):
            owners[tuple(w[i:i + 10])].add(str(item))
            sizes.add(len(w[i:i + 10]))
    out = {}
    for doc, text in docs:
        w = split(text)
        hit, found = set(), set()
        for n in sizes:
            for i in range(len(w) - n + 1):
                if (x := tuple(w[i:i + n])) in owners:
                    hit.update(range(i, i + n))
                    found |= owners[x]
        out[doc] = (len(w), len(hit), len(found), sha(",".join(sorted(found))), bool(hit))
    return out


def plain_verdicts(rows):
    """(id, host, path, good, bad) rows -> sorted (id, quality, toxicity, keep), every posterior worked out for itself."""
    prob = lambda x: 1 / (1 + math.exp(-x))
    odds = lambda x: math.log(min(max(x, 1e-3), 1 - 1e-3) / (1 - min(max(x, 1e-3), 1 - 1e-3)))

    def strength(groups):
        means = [sum(g) / len(g) for g in groups]
        m = sum(means) / len(means)
        v = sum((x - m) ** 2 for x in means) / len(means)
        between = max(v - sum(x * (1 - x) / len(g) for x, g in zip(means, groups)) / len(means), 1e-4)
        return min(max(m * (1 - m) / between - 1, 1.0), 1000.0)

    out = [[r[0]] for r in rows]
    for k in (3, 4):
        p = [round(prob(r[k]) * 1e6) / 1e6 for r in rows]
        hosts, paths = defaultdict(list), defaultdict(list)
        for r, x in zip(rows, p):
            hosts[r[1]].append(x)
            paths[r[1], r[2]].append(x)
        world, kh, kp = sum(p) / len(p), strength(list(hosts.values())), strength(list(paths.values()))
        for o, r, x in zip(out, rows, p):
            host = (sum(hosts[r[1]]) - x + kh * world) / (len(hosts[r[1]]) - 1 + kh)
            site = (sum(paths[r[1], r[2]]) - x + kp * host) / (len(paths[r[1], r[2]]) - 1 + kp)
            o.append(round(prob(r[k] + odds(site) - odds(world)), 6))
    return sorted((i, good, bad, good >= 0.5 and bad < 0.5) for i, good, bad in out)


def plain_lines(rows, ratio=0.05, least=5):
    """(doc_id, text, source) rows -> their texts without their source's frequent lines."""
    total, seen = defaultdict(int), defaultdict(int)
    for _, text, source in rows:
        total[source] += 1
        for x in {x for x in (text or "").split("\n") if x.strip(" ")}:
            seen[source, x] += 1
    out = []
    for _, text, source in rows:
        kept = [x for x in (text or "").split("\n") if not x.strip(" ") or seen[source, x] < least or seen[source, x] <= ratio * total[source]]
        out.append("\n".join(kept) if any(x.strip(" ") for x in kept) else text)
    return out


def plain_near(rows, size=5, tenths=8):
    """(doc_id, text) rows -> the ids that stay, one for each class of texts that share 0.8 of their shingles."""
    sets = {}
    for i, text in rows:
        words = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(ASCII_LOWER))
        sets[i] = {tuple(words[k:k + size]) for k in range(max(1, len(words) - size + 1))} if words else set()
    texts, ids = {i: t or "" for i, t in rows}, [i for i, _ in rows]
    edges = [(a, b) for n, a in enumerate(ids) for b in ids[:n]
             if texts[a] == texts[b] or sets[a] and sets[b] and 10 * len(sets[a] & sets[b]) >= tenths * len(sets[a] | sets[b])]
    return set(plain_components(ids, edges).values())


def plain_cut(text, items, size=10):
    """The text without the words of any item's windows; None if no other word is left."""
    split = lambda t: [m.span() for m in re.finditer(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", t.translate(ASCII_LOWER))]
    windows = set()
    for t in items:
        w = [(t or "").translate(ASCII_LOWER)[a:b] for a, b in split(t or "")]
        windows |= {tuple(w[i:i + size]) for i in range(max(1, len(w) - size + 1))} if w else set()
    sizes = {len(w) for w in windows}
    while text:
        at = split(text)
        w = [text.translate(ASCII_LOWER)[a:b] for a, b in at]
        hit = [False] * len(w)
        for n in sizes:
            for i in range(len(w) - n + 1):
                if tuple(w[i:i + n]) in windows:
                    hit[i:i + n] = [True] * n
        if not any(hit):
            return text
        if all(hit):
            return None
        for i in range(len(w) - 1, -1, -1):
            if hit[i] and (i + 1 == len(w) or not hit[i + 1]):
                last = at[i][1]
            if hit[i] and (i == 0 or not hit[i - 1]):
                text = text[:at[i][0]] + text[last:]
    return text
