"""Plain Python versions that the operators are held against."""

import re
from collections import Counter, defaultdict

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def fold(text):
    return re.sub("[A-Z]+", lambda m: m[0].lower(), text)


def shingle_set(text, width=5):
    w = WORD.findall(fold(text or ""))
    return {tuple(w[i : i + width]) for i in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())


def components(texts, percent=75):
    """Least id reachable by links, for each id of a dictionary of texts."""
    sets = {i: shingle_set(t) for i, t in texts.items()}
    where = defaultdict(list)
    for i, s in sets.items():
        for g in s:
            where[g].append(i)
    shared = Counter()
    for ids in where.values():
        for x in range(len(ids)):
            for y in range(x):
                shared[min(ids[x], ids[y]), max(ids[x], ids[y])] += 1
    up = {i: i for i in texts}

    def root(i):
        while up[i] != i:
            up[i] = up[up[i]]
            i = up[i]
        return i

    for (a, b), n in shared.items():
        if 100 * n >= percent * (len(sets[a]) + len(sets[b]) - n):
            a, b = root(a), root(b)
            up[max(a, b)] = min(a, b)
    return {i: root(i) for i in texts}


def quality_measures(text):
    w = WORD.findall(text)
    lines = Counter(line for line in text.split("\n") if WORD.search(line))
    chars = sum(map(len, w))
    covered, repeat_words = {}, 0
    for n in (3, 5, 6, 7, 8, 9, 10):
        grams = [tuple(w[i : i + n]) for i in range(len(w) - n + 1)]
        counts, seen, inside, again = Counter(grams), set(), set(), set()
        for i, g in enumerate(grams):
            if counts[g] > 1:
                inside.update(range(i, i + n))
            if g in seen:
                again.update(range(i, i + n))
            seen.add(g)
        if n == 3:
            repeat_words = len(inside)
        else:
            covered[n] = sum(len(w[i]) for i in again)
    return {
        "n_words": len(w), "word_chars": chars, "n_symbols": len(re.findall(r"[#*$%&|<>]", text)), "n_dup_lines": sum(c - 1 for c in lines.values()), "n_repeat_words": repeat_words,
        "dup_line_chars": sum((c - 1) * len("".join(WORD.findall(line))) for line, c in lines.items()), **{f"covered_{n}": c for n, c in covered.items()},
    }


def quality_verdict(text):
    m = quality_measures(text)
    if m["n_words"] < 50 or 100 * m["n_repeat_words"] > 50 * m["n_words"]:
        return False
    limits = {5: 15, 6: 14, 7: 13, 8: 12, 9: 11, 10: 10}
    return not (100 * m["dup_line_chars"] > 20 * m["word_chars"] or 100 * m["n_symbols"] > 10 * m["n_words"] or any(100 * m[f"covered_{n}"] > most * m["word_chars"] for n, most in limits.items()))
