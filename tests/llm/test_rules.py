"""Signature rules against a plain reading of them: labels and score of every text."""

import re
from collections import Counter

import pytest

from keyless.llm import licenses
from tests.llm.conftest import rows_of
from tests.llm.test_operators import got

SAMPLES = [
    "Licensed under the Apache License, Version 2.0 (the \"License\")", "This file is part of X. GNU General Public License v3 or later", "SPDX-License-Identifier: MIT",
    "released into the public domain; see the LICENSE file for details", "Llama 3.1 Community License Agreement", "Redistributions of source code must retain the above copyright notice",
    "may not be copied or used in any way without prior written permission", "The Software shall be used for Good, not Evil.", "EULA", "for research purposes only", "Zope Public License 2.1",
    "PolyForm Noncommercial License", "dual-licensed under MIT and CC-BY-SA 4.0", "copyright (c) 2019 2020 someone, all rights reserved", "the art of licensing", "fair use of apple pie",
]


def slow(text):
    words = [w for w in re.split(licenses.SEPARATOR, text or "") if w]
    low = ["".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in w) for w in words]
    line, found, base = " " + " ".join(low) + " ", [], []
    place = lambda m: line[: m.start()].count(" ")
    for number, (label, rank, keys, body) in enumerate(licenses.rules()):
        for m in re.finditer(f" (?:{body})(?= )", line) if set(keys.split("|")) & set(low) else ():
            found.append((place(m), -m.group().count(" "), rank, number, label))
    for phrase, label in licenses.BASE:
        base += [(place(m), label) for m in re.finditer(f" {phrase}(?= )", line)]
    kept, end, held, covered = [], -1, 0, 0
    for start, minus, rank, _, label in sorted(found):
        stop = start - minus
        inside = stop <= end
        if not inside or rank < held:
            kept.append(label)
        held = held if inside else rank
        covered += max(0, stop - max(end, start))
        end = max(end, stop)
    names = lambda xs: ",".join(sorted(set(xs)))
    at = [i for i, _ in base]
    return len(words), len(base), min(at, default=None), max(at, default=None), names(x for _, x in base), names([x for _, x in base] + kept), round(min(1.0, covered / len(words)), 9) if kept else 0.0


@pytest.mark.parametrize("which", ["sf", "edge", "samples"])
def test_labels_and_score(spark, request, which, tmp_path):
    if which == "samples":
        spark.createDataFrame(list(enumerate(SAMPLES)), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    folder = str(tmp_path) if which == "samples" else request.getfixturevalue(which)
    have = Counter((r["doc_id"], r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"], r["labels"], round(r["score"], 9)) for r in got(spark, 5, folder))
    assert have == Counter((d, *slow(t)) for d, t in rows_of(spark, folder))


def test_a_keyword_is_a_word_of_what_matches():
    """Phrases without choices hold their keyword; rules are told apart."""
    rules = licenses.rules()
    assert len(licenses.BY_HAND) == len(set(licenses.BY_HAND))
    for _, _, keys, body in rules:
        if re.fullmatch("[a-z0-9 ]+", body):
            assert set(keys.split("|")) & set(body.split(" ")), body
