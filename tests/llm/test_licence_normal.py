"""Normalisation, and the scan against a brute force that shares no code with it."""

import random

from foldstar.llm import licences as S


def slow_words(text):
    """Character by character: no pattern of the module is used."""
    out = []
    for line in text.split("\n"):
        low = line.lower()
        bare = low.lstrip(" \t/*#;-•(").strip()
        if (bare.startswith("copyright") or line.strip().startswith("©")) and any(str(y) in low for y in range(1900, 2100)):
            continue
        tokens, now = [], ""
        for c in low + " ":
            if c.isalnum() or c == "+" and (now == "" or now.endswith("+") or now.isalnum()):
                now += c
            else:
                tokens += [now] if now else []
                now = c if c == "+" else ""
        out.append(tokens)
    return [S.VARIANTS.get(w, w) for line in out for w in line]


def pairs(words):
    return {(a, b) for a, b in zip(words, words[1:])}


def test_marks_copyright_and_spelling():
    mit = next(t for n, t in S.TEMPLATES if n == "MIT" and "MERCHANTABILITY" in t)
    words = mit.split()
    block = "/*\n * Copyright (c) 2019 A. Person\n *\n" + "".join(f" * {' '.join(words[i : i + 11])}\n" for i in range(0, len(words), 11)) + " */\ncode();\n"
    scanner = S.Scanner()
    name, dice, _ = scanner.whole(block)
    assert (name, dice) == ("MIT", 1.0)
    assert scanner.whole("This work is licenced under the GNU General Public Licence, version 3.")[:2] == ("GPL-3.0", 1.0)
    assert S.words_of("1. One\n(a) Two\n- Three\n# Four\nCopyright 2020 X\nfive") == ["one", "two", "three", "four", "five"]
    assert S.words_of("copyright law applies to C++ and a-b") == ["copyright", "law", "applies", "to", "c++", "and", "a", "b"]


def test_full_texts_are_told_apart():
    scanner = S.Scanner()
    for name, text in S.TEMPLATES:
        got = scanner.whole("Some words before. " + text + " And some words after it.")
        assert got[0] == name and got[1] >= 0.99, (name, got)


def test_best_run_against_slow_brute_force():
    r = random.Random(4)
    short = [(n, t) for n, t in S.TEMPLATES if len(t.split()) < 14]
    scanner = S.Scanner(short)
    for _ in range(30):
        w = " ".join(r.choice(short)[1] for _ in range(2)).split()
        for _ in range(r.randint(0, 3)):
            w[r.randrange(len(w))] = r.choice(["x", "the", "licence", "under"])
        text = "Copyright 2021 Somebody\n" + " ".join(["some", "words"] * r.randint(0, 2) + w)
        words = slow_words(text)
        found = []
        for i, (_, t) in enumerate(short):
            b = pairs(slow_words(t))
            for p in range(len(words)):
                for q in range(p + 2, len(words) + 1):
                    a = pairs(words[p:q])
                    d = 2 * len(a & b) / (len(a) + len(b))
                    if d >= 0.8:
                        found.append((-d, -len(b), i))
        best = min(found, default=None)
        got = scanner.window(text)
        assert (got is None) == (best is None) and (best is None or (-got[0], got[1]) == (best[0], best[2])), text


def test_ties_go_to_the_first_template():
    same = (("A", "Licensed under the Some License."), ("B", "Licensed under the Some License."))
    assert S.Scanner(same).whole("licensed under the some license")[0] == "A"
