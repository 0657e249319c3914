"""Plain single-machine versions of the operators, for small tables."""

import re

import numpy as np
import xxhash


def simhash(texts: dict) -> dict:
    """doc_id -> (fingerprint, component) from {doc_id: text}, all pairs compared."""
    prints = {}
    for key, text in texts.items():
        words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
        hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
        prints[key] = sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes)) if hashes else 0
    keys = sorted(prints)
    fp = np.array([prints[k] for k in keys], np.uint64)
    root = np.arange(len(keys))
    near = [np.flatnonzero(np.bitwise_count(fp ^ f) <= 2) for f in fp]
    changed = True
    while changed:
        new = np.array([root[n].min() for n in near])
        changed = bool((new != root).any())
        root = new
    return {k: (f"{prints[k]:016x}", keys[root[i]]) for i, k in enumerate(keys)}


WORD = r"[^\x20\x09-\x0D]+"
ITEM_WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def _folded(text):
    return re.findall(ITEM_WORD, "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or ""))


def leaks(texts: list, items: dict, window: int = 10) -> list:
    """(n_words, hit positions, items) for each text."""
    patterns = {}
    for key, text in items.items():
        words = _folded(text)
        for i in range(max(1, len(words) - window + 1) if words else 0):
            patterns.setdefault(tuple(words[i : i + window]), set()).add(str(key))
    out = []
    for text in texts:
        words, hit, found = _folded(text), set(), set()
        for pattern, owners in patterns.items():
            for i in range(len(words) - len(pattern) + 1):
                if tuple(words[i : i + len(pattern)]) == pattern:
                    hit.update(range(i, i + len(pattern)))
                    found |= owners
        out.append((len(words), sorted(hit), sorted(found)))
    return out


def repeats(texts: list, window: int) -> list:
    """Words left of each text."""
    split, met = [re.findall(WORD, t or "") for t in texts], {}
    for words in split:
        for i in range(len(words) - window + 1):
            met[tuple(words[i : i + window])] = met.get(tuple(words[i : i + window]), 0) + 1
    out = []
    for words in split:
        gone = set()
        for i in range(len(words) - window + 1):
            if met[tuple(words[i : i + window])] > 1:
                gone.update(range(i, i + window))
        out.append([w for i, w in enumerate(words) if i not in gone])
    return out


def base(text) -> tuple:
    """(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words)."""
    words = re.findall(WORD, text or "")
    seen, dup = set(), 0
    for line in (text or "").split("\n"):
        if re.search(WORD, line):
            dup += line in seen
            seen.add(line)
    runs = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    covered = {j for i, r in enumerate(runs) if runs.count(r) > 1 for j in range(i, i + 8)}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), dup, len(covered)


def kept_lines(docs: list) -> list:
    """Texts of (id, text) without the lines of later windows of three; ids distinct and not null."""
    windows = {}
    for key, text in docs:
        lines = [(i, line) for i, line in enumerate((text or "").split("\n")) if re.search(WORD, line)]
        for k in range(len(lines) - 2):
            windows.setdefault(tuple(line for _, line in lines[k : k + 3]), []).append((key, [i for i, _ in lines[k : k + 3]]))
    gone = {}
    for places in windows.values():
        for key, at in sorted(places)[1:]:
            gone.setdefault(key, set()).update(at)
    return [None if t is None else "\n".join(line for i, line in enumerate(t.split("\n")) if i not in gone.get(k, ())) for k, t in docs]


def packed(items: list, capacity: int, per_source: int) -> list:
    """(bin, offset) for (size, source, cluster) by trying every bin for each item."""
    bins, out = [], []
    for size, source, cluster in items:
        best = None
        for b, (left, held) in enumerate(bins):
            fits = left >= size and all(c != cluster for _, c in held) and sum(s == source for s, _ in held) < per_source
            if fits and (best is None or left < bins[best][0]):
                best = b
        if best is None:
            bins.append([capacity, []])
            best = len(bins) - 1
        out.append((best, capacity - bins[best][0]))
        bins[best][0] -= size
        bins[best][1].append((source, cluster))
    return out


def latent_class(votes: list, guess: list, weights: list, share: float, share_weight: float, turns: int) -> list:
    """P(good) of each text of a list of votes, text by text: guess[class][rule][vote] counts weights[class][rule] x texts as prior."""
    n, rules = len(votes), len(votes[0])
    told, good, first = guess, [], share
    for turn in range(turns + 1):
        good = []
        for row in votes:
            p = [1 - share, share]
            for c in (0, 1):
                for r, v in enumerate(row):
                    p[c] *= told[c][r][v]
            good.append(p[1] / (p[0] + p[1]))
        told = [[[0.0] * 3 for _ in range(rules)] for _ in range(2)]
        for c in (0, 1):
            for r in range(rules):
                sums = [weights[c][r] * n * guess[c][r][v] for v in range(3)]
                for row, g in zip(votes, good):
                    sums[row[r]] += g if c else 1 - g
                told[c][r] = [s / sum(sums) for s in sums]
        share = (sum(good) + first * share_weight * n) / (n * (1 + share_weight))
    return good
