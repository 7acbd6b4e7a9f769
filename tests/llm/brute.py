"""Plain readings of the operators' definitions, for small tables."""

import collections
import itertools
import re
import zlib

SPACES = " \t\n\x0b\x0c\r"


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def base(text):
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed."""
    w = words(text)
    lines = [x for x in (text or "").split("\n") if words(x)]
    windows = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
    often = collections.Counter(windows)
    covered = {i + k for i, x in enumerate(windows) if often[x] > 1 for k in range(3)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(covered), len(w) < 50 or 100 * len(covered) > 50 * len(w)


def ascii_lower(s):
    return "".join(c.lower() if "A" <= c <= "Z" else c for c in s)


def line_dedup(docs):
    """doc rows (id, text) → list of (n_lines, n_dropped, kept text) in order."""
    split = [(i, (t or "").split("\n")) for i, t in docs]
    key = lambda line: ascii_lower(line.strip(SPACES))
    held = {}
    for n, (i, lines) in enumerate(split):
        for k in {key(x) for x in lines}:
            held.setdefault(k, []).append((n, i))
    made = []
    for i, lines in split:
        kept = []
        for x in lines:
            own = held[key(x)]
            ids = [d for _, d in own if d is not None]
            gone = len(key(x)) >= 20 and len(own) >= 3 and not (i is not None and ids and i == max(ids))
            if not gone:
                kept.append(x)
        made.append((len(lines), len(lines) - len(kept), "\n".join(kept)))
    return made


def components(ids, linked):
    """Least id of each id's component under a symmetric relation."""
    label = {i: i for i in ids}
    moved = True
    while moved:
        moved = False
        for a, b in itertools.combinations(sorted(set(ids)), 2):
            if label[a] != label[b] and linked(a, b):
                label[a] = label[b] = min(label[a], label[b])
                moved = True
    for _ in ids:
        label = {i: label[label[i]] for i in label}
    return label


def shingles(text, n=5):
    """Windows of words with their counts."""
    w = words((text or "").lower())
    return collections.Counter(tuple(w[i : i + n]) for i in range(max(1, len(w) - n + 1))) if w else collections.Counter()


def near(a, b, threshold=0.8):
    x, y = shingles(a), shingles(b)
    return bool(x and y) and (x & y).total() / (x | y).total() >= threshold


def crc(ids):
    return zlib.crc32(b"".join(int(i).to_bytes(4, "little") for i in ids))


RULES = (("org/", "allow"), ("example.org/es/", "block"), ("example.org/en/1", "block"), ("com/fr/", "allow"), ("com/de/", "block"))


def host_path(url):
    if not url or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    host = re.match(r"[^/?#]*", rest)[0]
    return ascii_lower(host), re.match(r"[^?#]*", rest[len(host) :])[0]


def rule(host, path):
    best = None
    for text, verdict in RULES:
        h, _, p = text.partition("/")
        if (host == h or host.endswith("." + h)) and path.startswith("/" + p) and (best is None or len(text) > len(best[0])):
            best = (text, verdict)
    return best or (None, None)
