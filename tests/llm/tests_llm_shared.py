"""Brute-force versions that several tests hold results against."""

import re
import string
from collections import Counter, defaultdict

import public_tokenizers as P


def clip_ids(text):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(P.path("word_bpe_49k.json")).encode(text or "", add_special_tokens=False).ids


WORD, FOLD = re.compile(r"[^\x20\x09-\x0D]+"), {ord(a): a.lower() for a in string.ascii_uppercase}


def shingle_set(text):
    w = WORD.findall((text or "").translate(FOLD))
    return frozenset(tuple(w[i : i + 5]) for i in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)]) if w else frozenset()


def brute_components(docs):
    parent = {d: d for d, _ in docs}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    sets = [(d, shingle_set(t)) for d, t in docs]
    for i, (d, a) in enumerate(sets):
        for e, b in sets[:i]:
            if a and b and 100 * len(a & b) >= 75 * len(a | b):
                x, y = find(d), find(e)
                parent[max(x, y)] = min(x, y)
    return {d: find(d) for d, _ in docs}


def brute_lines(docs, least):
    key = lambda line: line.strip("\x20\x09\x0a\x0b\x0c\x0d").translate(FOLD)
    seen = defaultdict(set)
    for n, (d, t) in enumerate(docs):
        for line in (t or "").split("\n"):
            seen[key(line)].add(d if d is not None else ("no id", t))
    often = {k for k, v in seen.items() if len(v) >= least and k}
    out = []
    for d, t in docs:
        lines = (t or "").split("\n")
        kept = [x for x in lines if key(x) not in often]
        out.append((d, len(lines), len(lines) - len(kept), "\n".join(kept)))
    return Counter(out)
