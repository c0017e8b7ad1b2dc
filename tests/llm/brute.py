"""Plain definitions of the operators, for small inputs."""

import collections
import hashlib
import html
import re

SPACE = re.compile("[^\x20\x09-\x0d]+")
ALNUM = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")


def fold(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")


def shingles(text, width):
    words = SPACE.findall(fold(text))
    if len(words) >= width:
        return {tuple(words[i : i + width]) for i in range(len(words) - width + 1)}
    return {tuple(words)} if words else set()


def near(rows, width=3, percent=85):
    """doc_id -> (n_shingles, component)."""
    sets = [(i, shingles(t, width)) for i, t in rows]
    parent = {i: i for i, _ in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for k, (i, a) in enumerate(sets):
        for j, b in sets[:k]:
            if a and b and 100 * len(a & b) >= percent * len(a | b):
                x, y = find(i), find(j)
                parent[max(x, y)] = min(x, y)
    return {i: (len(s), find(i)) for i, s in sets}


def substring(rows, width=20):
    """doc_id -> (words, kept text)."""
    seen, out = {}, {}
    for i, text in sorted(rows):
        words = SPACE.findall(text or "")
        gone = [False] * len(words)
        for s in range(len(words) - width + 1):
            key = tuple(words[s : s + width])
            if seen.setdefault(key, (i, s)) != (i, s):
                gone[s : s + width] = [True] * width
        out[i] = (len(words), " ".join(w for w, g in zip(words, gone, strict=True) if not g))
    return out


def contaminated(rows, items, width=10):
    """doc_id -> (words, hit words, items)."""
    windows = collections.defaultdict(set)
    for k, text in items:
        words = ALNUM.findall(fold(text))
        n = min(width, len(words))
        for s in range(len(words) - n + 1 if n else 0):
            windows[tuple(words[s : s + n])].add(str(k))
    out = {}
    for i, text in rows:
        words = ALNUM.findall(fold(text))
        hit, found = set(), set()
        for w, names in windows.items():
            for s in range(len(words) - len(w) + 1):
                if tuple(words[s : s + len(w)]) == w:
                    hit.update(range(s, s + len(w)))
                    found |= names
        out[i] = (len(words), len(hit), sorted(found))
    return out


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


def page_text(page, bounded):
    """The main text of a simple page: its furniture cut out by patterns, then each line judged by the lines around it."""
    page = re.sub(r"<!--.*?-->|<!doctype[^>]*>|<(script|style|title)\b.*?</\1>", "", page, flags=re.S | re.I)
    page = re.sub(r"<(head|nav)\b.*?</\1>|<footer\b.*?(</footer>|\Z)|<div class=\"ad\">.*?</div>", "\n\x00\n", page, flags=re.S)
    inside = re.search(r"<article>(.*?)</article>", page, flags=re.S)
    if bounded and inside:
        page = inside[1]
    page = re.sub(r"<br>", " ", re.sub(r"[\n\t]+(?!\x00)(?<!\x00\n)", " ", page))
    page = re.sub(r"</?(p|h1|div|article|ul|li|html|body)\b[^>]*>", "\n", page)
    lines = [" ".join(html.unescape(re.sub(r"</?(b|a|meta)\b[^>]*>", "", x)).split()) for x in page.split("\n")]
    lines = [x.replace("\x00", "") for x in lines if x]
    if bounded:
        return "\n".join(x for x in lines if x)
    sums = [sum(map(len, lines[i : i + 3])) for i in range(len(lines))]
    surge = min(80, max(sums, default=0) / 2)
    kept = set()
    for i, x in enumerate(sums):
        if x > surge:
            # All lines that hang together with the window, without three empty ones in a row; then back to the start of its run.
            j = next(k for k in range(i, len(lines)) if lines[k])
            while j > 0 and lines[j - 1]:
                j -= 1
            while j < len(lines) and sums[j]:
                kept.add(j)
                j += 1
    return "\n".join(lines[i] for i in sorted(kept) if lines[i])
