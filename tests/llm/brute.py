"""Plain versions of the operators, for comparison on small tables."""

import hashlib
import math
import re
from collections import defaultdict

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def components(nodes, links):
    parent = {n: n for n in nodes}

    def root(n):
        while parent[n] != n:
            n = parent[n] = parent[parent[n]]
        return n

    for a, b in links:
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)
    return {n: root(n) for n in nodes}


def repeats(docs, window=13):
    """{doc_id: (n_words, n_removed, sha256)}"""
    words = {d: WORD.findall(t or "") for d, t in docs}
    least = {}
    for d in sorted(words):
        for i in range(len(words[d]) - window + 1):
            least.setdefault(tuple(words[d][i : i + window]), d)
    out = {}
    for d, ws in words.items():
        gone = set()
        for i in range(len(ws) - window + 1):
            if least[tuple(ws[i : i + window])] < d:
                gone.update(range(i, i + window))
        kept = [w for i, w in enumerate(ws) if i not in gone]
        out[d] = (len(ws), len(gone), hashlib.sha256(" ".join(kept).encode()).hexdigest())
    return out


def shingles(text, k):
    words = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    if not words:
        return frozenset()
    return frozenset(tuple(words[i : i + k]) for i in range(max(1, len(words) - k + 1)))


def jaccard_groups(docs, k=4, threshold=85):
    """{doc_id: (n_shingles, component)}"""
    sets = {d: shingles(t, k) for d, t in docs}
    holders = defaultdict(list)
    for d, s in sets.items():
        for x in s:
            holders[x].append(d)
    common = defaultdict(int)
    for ds in holders.values():
        for i, a in enumerate(ds):
            for b in ds[i + 1 :]:
                common[a, b] += 1
    links = [(a, b) for (a, b), c in common.items() if 100 * c >= threshold * (len(sets[a]) + len(sets[b]) - c)]
    of = components(list(sets), links)
    return {d: (len(s), of[d]) for d, s in sets.items()}


def mixed(docs, weights=(5, 2, 1), share=1.5, most=2.0, seed="mix-1"):
    """(doc_id, text) of the mix of (doc_id, source, text): whole epochs, then hash-random order up to each budget, the last text cut."""
    from factbench.llm.mixture import water_level

    sources = defaultdict(list)
    for d, s, t in docs:
        sources[s].append((hashlib.md5(f"{seed}:{d}".encode()).hexdigest(), len(WORD.findall(t)), d, t))
    names = sorted(sources, key=lambda s: (s is None, s))
    sizes = [sum(n for _, n, *_ in sources[s]) for s in names]
    out = []
    for s, size, target in zip(names, sizes, water_level(sizes, [weights[i % len(weights)] for i in range(len(names))], share, most), strict=True):
        left = math.floor(target)
        while left > 0:
            for _, n, d, t in sorted(sources[s]):
                take = min(n, left)
                left -= take
                if take:
                    out.append((d, t if take == n else t[: list(WORD.finditer(t))[take - 1].end()]))
    return out


def url_verdicts(pages, labels, depth=8, fan=20, rare=0.05, z=1.96, few=5, support=30, close=0.1, strength=10.0, reject=0.5):
    """{page_id: (template, impurity, bad)} by a plain recursion over (page_id, host, path) pages and a dict of labels; rules aside."""

    def shape(s):
        return re.sub(r"(?<!\{)[0-9]+", "{num}", re.sub(r"^(?=.*[0-9])[0-9A-Fa-f-]{8,}", "{hex}", s))

    def mean(rows):
        known = [labels[p] for p, _ in rows if p in labels]
        return len(known), sum(known)

    def smooth(rows, toward):
        n, bad = mean(rows)
        return (bad + strength * toward) / (n + strength), n + strength

    def walk(rows, level, template, share, backing):
        """``rows`` are (page_id, segments) of one template so far."""
        kids = defaultdict(list)
        for p, segs in rows:
            kids[segs[level] if len(segs) > level else ""].append((p, segs))
        n, bad = mean(rows)
        merged = defaultdict(list)
        for child, own in kids.items():
            k, k_bad = mean(own)
            named = child
            if child and len(kids) > 1:
                apart = False
                if k and n > k:
                    off = abs(k_bad / k - (bad - k_bad) / (n - k))
                    error = math.sqrt(bad / n * (1 - bad / n) * (1 / k + 1 / (n - k)))
                    apart = off > z * error or k >= support and off > close
                if len(kids) > fan and len(own) < rare * len(rows) and k < few or not apart:
                    named = "*"
            merged[named] += own
        for named, own in merged.items():
            new, back = smooth(own, share)
            if back == backing:
                new = share
            if named == "":
                least = new - z * math.sqrt(new * (1 - new) / back)
                for p, _ in own:
                    out[p] = (template, new, new > reject or least > prior)
            else:
                walk(own, level + 1, f"{template}/{named}", new, back)

    out, hosts = {}, defaultdict(list)
    for p, host, path in pages:
        segs = [shape(s) for s in path.split("/") if s]
        hosts[host].append((p, segs if len(segs) <= depth else [*segs[: depth - 1], "/".join(segs[depth - 1 :])]))
    n, bad = mean([row for rows in hosts.values() for row in rows])
    prior = bad / n if n else 0.0
    for host, rows in hosts.items():
        walk(rows, 0, host, *smooth(rows, prior))
    return out
