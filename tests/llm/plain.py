"""Plain versions of operators, written for small tables."""

import collections
import math
import re

from pyspark.sql import functions as F

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def lower(text):
    return re.sub("[A-Z]", lambda m: m.group().lower(), text or "")


def shingles(text, width=5):
    words = (text or "").encode().lower().split()
    return {tuple(words[k : k + width]) for k in range(max(1, len(words) - width + 1))}


def near_groups(texts):
    """Id to the smallest id of its component, links being a Jaccard similarity of 0.8; texts by id."""
    sets = {i: shingles(t) for i, t in texts.items()}
    root = {i: i for i in texts}
    ids = sorted(texts)
    for b in ids:
        for a in ids:
            if a < b and 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]) and root[a] != root[b]:
                old, new = max(root[a], root[b]), min(root[a], root[b])
                root = {i: new if r == old else r for i, r in root.items()}
    return root


def contaminated(text, items, width=13):
    """Hit words, all words, and the verdict."""
    words = WORD.findall(lower(text))
    windows = set()
    for item in items:
        w = WORD.findall(lower(item))
        windows |= {tuple(w[k : k + width]) for k in range(max(1, len(w) - width + 1) if w else 0)}
    hit = set()
    for size in {len(w) for w in windows}:
        for k in range(len(words) - size + 1):
            if tuple(words[k : k + size]) in windows:
                hit |= set(range(k, k + size))
    return hit, words, bool(hit) and 20 * len(hit) >= len(words)


def exponent(shares, entropy_share, most_repeats):
    """The largest exponent with the wished entropy, raised to the least that keeps the limit of repetition; by bisection."""
    if len(shares) < 2:
        return 1.0

    def entropy(a):
        raw = [p**a for p in shares]
        return -sum(x / sum(raw) * math.log(x / sum(raw)) for x in raw)

    def repeats(a):
        raw = [p ** (a - 1) for p in shares]
        return max(raw) / min(raw)

    def last(fits):
        if fits(1.0):
            return 1.0
        low, high = 0.0, 1.0
        for _ in range(60):
            middle = (low + high) / 2
            low, high = (middle, high) if fits(middle) else (low, middle)
        return low

    found = 1.0 if most_repeats is None else 0.0
    if entropy_share is not None:
        found = last(lambda a: entropy(a) >= entropy_share * math.log(len(shares)) - 1e-12)
    if most_repeats is not None and repeats(0.0) > most_repeats:
        found = max(found, last(lambda a: repeats(a) > most_repeats))
    return found


def uses(rows, spark, weights, least_rows, block_tokens, seed=0):
    """``(row number, copy, block)`` of every use. ``rows`` are ``(key, tokens, h, id)``, ``weights`` key to target tokens."""
    by_key = collections.defaultdict(list)
    for number, (key, tokens, h, id_) in enumerate(rows):
        by_key[key].append((h, (id_ is not None, id_ or 0), number, tokens))
    budget, out = sum(weights.values()), []
    blocks = max(1, math.ceil(budget / block_tokens))
    for key, mine in by_key.items():
        epoch, n_parts = sum(t for *_, t in mine), math.ceil(len(mine) / max(float(least_rows), len(rows) / 65536))
        parts = collections.defaultdict(list)
        for h, tie, number, tokens in sorted(mine):
            parts[math.floor((h % (1 << 40)) / float(1 << 40) * n_parts)].append((number, tokens))
        copies = math.ceil(weights[key] / epoch)
        pairs = spark.createDataFrame([(c, p) for c in range(copies) for p in parts], "copy int, part int")
        turned = {(r.copy, r.part): r.x for r in pairs.select("copy", "part", F.xxhash64(F.lit(seed), "copy", "part").alias("x")).collect()}
        at = 0
        for copy in range(copies):
            for part in sorted(parts, key=lambda p, c=copy: (turned[c, p], p)):
                for number, tokens in parts[part]:
                    if at < weights[key]:
                        out.append((number, copy, min(blocks - 1, math.floor(at / weights[key] * blocks))))
                    at += tokens
    return out
