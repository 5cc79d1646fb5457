"""Plain versions of operators, for comparison."""

import hashlib

import numpy as np

from vecgraph.llm import decontaminate


def contamination(texts, items, window=10):
    """(words, hit words, ids of items that occur) per text, by comparing every window with every place."""
    out = []
    for text in texts:
        w = decontaminate.words((text or "").encode())
        hit, named = set(), []
        for name, body in items:
            b = decontaminate.words((body or "").encode())
            n = min(len(b), window)
            seen = False
            for i in range(len(b) - n + 1 if n else 0):
                for j in range(len(w) - n + 1):
                    if w[j : j + n] == b[i : i + n]:
                        hit |= set(range(j, j + n))
                        seen = True
            if seen:
                named.append(name)
        out.append((len(w), len(hit), named))
    return out


def ids_digest(names):
    return hashlib.sha256(",".join(sorted(n for n in names if n is not None)).encode()).hexdigest()


def trigrams(text):
    """Trigrams of letters and single bounds between words, with their counts."""
    marked = " " + "".join(c if c.isalpha() else " " for c in text.lower()) + " "
    while "  " in marked:
        marked = marked.replace("  ", " ")
    out = {}
    for i in range(len(marked) - 2):
        out[marked[i : i + 3]] = out.get(marked[i : i + 3], 0) + 1
    return out if any(c.isalpha() for c in text) else {}


def languages(train, texts, dims, seed=17):
    """(language, cosine) per text: every letter's vector drawn, permuted by its place, multiplied and added one by one."""
    letters = {}

    def vector(gram):
        v = np.ones(dims)
        for place, c in zip((2, 1, 0), gram, strict=True):
            if c not in letters:
                letters[c] = np.random.Generator(np.random.Philox(key=[seed, ord(c)])).integers(0, 2, dims, np.int8) * 2.0 - 1
            v = v * np.roll(letters[c], place)
        return v

    def bundle(grams):
        return sum((n * vector(g) for g, n in grams.items()), np.zeros(dims))

    learned = {}
    for lang, text in train:
        grams = trigrams(text or "")
        if lang is not None and grams:
            learned[lang] = learned.get(lang, 0) + bundle({g: n / sum(grams.values()) for g, n in grams.items()})
    out = []
    for text in texts:
        v = bundle(trigrams(text or ""))
        cos = {k: float(v @ p / (np.linalg.norm(v) * np.linalg.norm(p))) for k, p in learned.items()} if v.any() else {}
        best = max(sorted(cos), key=cos.get, default="und")
        out.append((best, cos.get(best, 0.0)))
    return out
