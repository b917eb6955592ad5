"""Licence statements over line breaks, near each other, and against plain windows."""

import re
from collections import Counter

import pytest

licences = pytest.importorskip("bundlery.llm.licence_scan")
MIT = next(t for _, t in licences.TEMPLATES if t.startswith("Permission is hereby"))
GPL = "This work is licensed under the GNU General Public License, version 3."


def wrapped(text, words=9):
    w = text.split()
    return "\n".join(" * " + " ".join(w[i : i + words]) for i in range(0, len(w), words))


def plain(text):
    """Best windows without common words, by comparing every window with every template."""
    w = re.sub("[^a-z0-9]+", " ", text.lower()).split()
    grams, found = list(zip(w, w[1:])), []
    for i, (name, body) in enumerate(licences.TEMPLATES):
        v = re.sub("[^a-z0-9]+", " ", body.lower()).split()
        own = list(zip(v, v[1:]))
        for p in range(len(grams)):
            part = grams[p : p + len(own)]
            dice = 2 * (Counter(part) & Counter(own)).total() / (len(part) + len(own))
            if part[0] in own and dice >= 0.8 - 1e-12:
                found.append((-dice, -len(own), i, p, p + len(part), name))
    kept = []
    for x in sorted(found):
        if not any(x[3] <= y[4] and y[3] <= x[4] for y in kept):
            kept.append(x)
    return {(name): (n, round(max(-x[0] for x in kept if x[5] == name), 6)) for name, n in Counter(x[5] for x in kept).items()}


TEXTS = [
    "Some words here\nand there\n\n" + GPL.replace("GNU ", "GNU\n") + "\n\nmore words",
    wrapped(MIT),
    "Copyright 2020 Someone. All rights reserved.",
    GPL + "\nfor all",
    GPL + "\n\n" + GPL,
    "License\nGNU General",
    " ".join([GPL] * 40),
    "\n\n".join(t for _, t in licences.TEMPLATES),
    MIT.replace("free of charge", "at no cost").replace("publish, ", ""),
    GPL.replace("version 3", "version 9"),
    "words " * 5000 + GPL + " words" * 5000,
    None,
    "",
    "license",
]


def test_statements_are_those_of_plain_windows(spark):
    docs = spark.createDataFrame(list(enumerate(TEXTS)), "doc_id long, text string").repartition(3)
    got = {}
    for r in licences.scan_licences(docs).collect():
        got.setdefault(r["doc_id"], {})[r["licence"]] = (r["n_statements"], r["best_dice"])
    assert got == {i: want for i, t in enumerate(TEXTS) if (want := plain(t or ""))}
    assert got[0] == got[3] == got[10] == {"gpl-3.0": (1, 1.0)} and got[1] == {"mit": (1, 1.0)}
    assert got[4] == {"gpl-3.0": (2, 1.0)} and got[6] == {"gpl-3.0": (40, 1.0)}
    assert got[2] == {"all-rights-reserved": (1, 1.0)} and got[8]["mit"][1] < 1 and 5 not in got


def test_every_template_is_found_as_itself(spark):
    docs = spark.createDataFrame([(i, t) for i, (_, t) in enumerate(licences.TEMPLATES)], "doc_id long, text string")
    got = {(r["doc_id"], r["licence"]): r["best_dice"] for r in licences.scan_licences(docs).collect()}
    assert got == {(i, name): 1.0 for i, (name, _) in enumerate(licences.TEMPLATES)}


def test_rows_of_one_id_are_counted_together(spark):
    docs = spark.createDataFrame([(1, GPL), (1, GPL), (None, GPL)], "doc_id long, text string")
    assert {(r["doc_id"], r["n_statements"]) for r in licences.scan_licences(docs).collect()} == {(1, 2), (None, 1)}
