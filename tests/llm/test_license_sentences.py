"""op9: every line of every text is looked up, whatever its words and however a sentence is wrapped."""

import random
import re

from exactsum.llm import licenses


def brute(text):
    """The identifiers as the module's text defines them: all runs of whole lines of all pieces."""
    known, ids = licenses.lookup(), []
    for piece in re.sub(licenses.BREAK, lambda m: f"{m[1] or ''}\1", re.sub("\r\n?", "\n", text)).split("\1"):
        lines = [licenses.plain(x) for x in piece.split("\n")]
        found = [(i, j, known[s]) for i in range(len(lines)) for j in range(i, len(lines)) if lines[i] and lines[j] and (s := " ".join(lines[i : j + 1])) in known]
        ids += [x for i, j, x in found if not any(a <= i and b >= j and b - a > j - i for a, b, _ in found)]
    return ids


def judged(spark, texts):
    d = spark.createDataFrame([*enumerate(texts)], "doc_id long, text string")
    return [(r.sentence_ids, r.licenses) for r in licenses.recognised(d).orderBy("doc_id").collect()]


def test_sentences_without_common_words(spark):
    cases = {
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.": (["zero-bsd-grant"], ["0BSD"]),
        "All advertising materials mentioning features or use of this software must display the following acknowledgement:": (["bsd-advert"], []),
        "# All rights\n# reserved.\nx = 1": (["all-rights"], ["Proprietary"]),
        "All rights  reserved.": (["all-rights"], ["Proprietary"]),
        "This is free and unencumbered software released into the public\r\ndomain.": (["unlicense"], ["Unlicense"]),
    }
    assert judged(spark, cases) == [*cases.values()]


def test_sentences_of_a_word_a_line(spark):
    known = licenses.lookup()
    for between in (" ", "\n", "\n * "):
        assert [ids for ids, _ in judged(spark, [s.replace(" ", between) for s in known])] == [[x] for x in known.values()]


def test_sentences_that_share_lines(spark):
    both = 'This project is\nlicensed under the Apache License, Version 2.0\n(the "License");'
    inside = "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted\n, provided that the above copyright notice and this permission notice appear in all copies."
    many = "\n".join(["all rights reserved"] * 30_000)
    assert judged(spark, [both, inside, many]) == [(["apache2-notice"] * 2, ["Apache-2.0"]), (["isc-grant"], ["ISC"]), (["all-rights"] * 30_000, ["Proprietary"])]


def test_sentences_as_by_brute_force(spark):
    rng, known = random.Random(5), [*licenses.lookup()]
    gaps = [" "] * 6 + ["\n", "\r\n", "\n# ", " \n  ", ", ", ". ", "\n\n", "\n *\n", "\1", " é ", "-\n"]

    def text():
        words = []
        for _ in range(rng.randint(1, 6)):
            words += rng.choice(known).split()[rng.choice([0, 0, 0, 3]) :]
            words += [rng.choice(["", "", "x", "İ", "the"])]
        plain, out = rng.random() < 0.5, rng.choice(["", "\n", "* ", " \r"])
        for w in words:
            out += rng.choice([w, w, w.upper()]) + (rng.choice(gaps[:11]) if plain or rng.random() < 0.8 else rng.choice(gaps))
        return out if rng.random() < 0.5 else out.replace(" the", "\n\tthe").replace("x", "\n x\n")

    texts = [text() for _ in range(600)] + ["", "\n", "\n\n", "\1", "\n".join(known), "\n\n".join(known), ". ".join(known), "\n".join(known[::-1]).replace(" ", "\n")]
    texts += ["\n".join(x for k in rng.choices(known, k=6) for x in (k, *rng.choices(["", "x"], k=1))) for _ in range(100)]
    expected = [brute(t) for t in texts]
    assert sum(map(bool, expected)) > 300
    assert [ids for ids, _ in judged(spark, texts)] == expected
