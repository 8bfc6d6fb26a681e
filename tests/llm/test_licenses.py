"""Notices, wrapped, commented, several in one block, against a brute-force search."""

import random
import re
import textwrap

from cellstream.llm import licenses


def test_wrapped_and_several_notices(spark):
    mit = licenses.TEMPLATES["MIT"][2]
    texts = ["/*\n * " + mit.replace(" copy of ", " copy\n * of ") + "\n */", "Licensed under the GNU\nprose first. This work is licensed under the GNU General\nPublic License, version 3.", "Released under the MIT License. Licensed under the Apache License, Version 2.0."]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = sorted((r["doc_id"], r["start"], r["license"], r["confirmed"]) for r in licenses.scan(df).collect() if r["confirmed"])
    assert [(d, x, c) for d, _, x, c in got] == [(0, "MIT", True), (1, "GPL-3.0", True), (2, "MIT", True), (2, "Apache-2.0", True)]


def brute(text):
    """(license, words) of every template in the text as a regular expression over its words; longest first where they overlap."""
    words = [m.span() for m in re.finditer(r"[\w.-]*\w", text)]
    flat = " " + " ".join(text[a:b].lower() for a, b in words) + " "
    hits = []
    for name, texts in licenses.TEMPLATES.items():
        for t in texts:
            want = re.findall(r"[\w.-]*\w|(?<!\S)\*(?!\S)", t.lower())
            pattern = "".join(r"(?: \S+){1,8}?" if w == "*" else " " + re.escape(w) for w in want) + "(?= )"
            for m in re.finditer(f"(?={pattern})", flat):
                end = re.compile(pattern).match(flat, m.start()).end()
                first = flat[: m.start()].count(" ")
                hits.append((-flat[m.start() : end].count(" "), first, name))
    taken, out = set(), []
    for less, first, name in sorted(hits, key=lambda h: h[:2]):
        if taken.isdisjoint(range(first, first - less)):
            taken |= set(range(first, first - less))
            out.append((words[first][0], words[first - less - 1][1], name))
    return sorted(out)


def test_against_brute_force(spark):
    rng = random.Random(7)
    prose = [f"w{k}" for k in range(400)]
    every = [(n, t) for n, ts in licenses.TEMPLATES.items() for t in ts]
    texts = []
    for _ in range(120):
        parts = []
        for _ in range(rng.randint(1, 4)):
            words = [" ".join(rng.choices(prose, k=rng.randint(1, 3))) if w == "*" else w for w in rng.choice(every)[1].split()]
            if rng.random() < 0.3:
                words[rng.randrange(len(words))] = "altered"
            notice = " ".join(words)
            if rng.random() < 0.6:
                notice = textwrap.fill(notice, 60, initial_indent=" * ", subsequent_indent=rng.choice([" * ", "# ", "// "]))
            parts += [" ".join(rng.choices(prose, k=rng.randint(0, 900))), notice]
        texts.append("\n".join(parts))
    shared = licenses.TEMPLATES["BSD-2-Clause"][1].split(" 2. Redis")[0]
    texts += [shared, "a driving license is needed", "license " * 3000, None, "", "x " * 50_000 + licenses.TEMPLATES["Unlicense"][0]]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").selectExpr("*", "0 AS license", "1 AS block")
    got = {}
    for r in licenses.scan(df).collect():
        if r["confirmed"]:
            got.setdefault(r["doc_id"], []).append((r["start"], r["end"], r["license"]))
    want = {d: f for d, t in enumerate(texts) if t and (f := brute(t))}
    assert {d: sorted(f) for d, f in got.items()} == want and len(want) > 90 and 120 not in want


def test_altered_notices_get_the_nearest_template(spark):
    bsd = licenses.TEMPLATES["BSD-3-Clause"][1].replace("*", "the holder").replace("binary form must", "binary form should")
    gpl = licenses.TEMPLATES["GPL-2.0-or-later"][0].replace("version 2", "version 4")
    df = spark.createDataFrame([(0, bsd), (1, gpl)], "doc_id long, text string")
    got = {r["doc_id"]: r for r in licenses.scan(df).collect()}
    assert got[0]["license"] == "BSD-3-Clause" and not got[0]["confirmed"] and got[0]["differences"] == "-must +should"
    assert got[1]["license"] == "GPL-2.0-or-later" and not got[1]["confirmed"] and got[1]["n_differences"] == 1
