"""Licence scan against plain Python: base phrases by words, detections by patterns, suppression by intervals."""

import random
import re

from pyspark.sql import functions as F

from levelwave.llm.license_rules import BASE_PHRASES, rules
from levelwave.llm.licenses import gated, license_scan, scan

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOWER = str.maketrans({chr(65 + i): chr(97 + i) for i in range(26)})


def brute(text):
    words = WORD.findall((text or "").translate(LOWER))
    places, labels = [], set()
    for phrase, label in BASE_PHRASES:
        p = phrase.split()
        for i in range(len(words) - len(p) + 1):
            if words[i : i + len(p)] == p:
                places.append(i)
                labels.add(label)
    return len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(labels))


def test_base_phrases_equal_brute_force(spark):
    rng = random.Random(11)
    parts = ["mit", "license", "MIT", "License", " ", "-", "\n", "cc", "CC", "by", "gnu general public license", "Apache License, Version 2.0", "é", "ß", "K", "İ", "licensé", "0", ".", "accby", "\x00", "nc"]
    texts = [None, "", " ", "MIT\n--license", "mit license mit license", "cc by cc-by", "the MIT licence", "word"] + ["".join(rng.choice(parts) + rng.choice(["", " ", " "]) for _ in range(rng.randint(0, 25))) for _ in range(600)]
    docs = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)] + [(None, "MIT License", 1), (3, texts[3], 1)], "doc_id long, text string, norm int")
    got = license_scan(docs).collect()
    assert len(got) == len(texts) + 2
    for r in got:
        text = "MIT License" if r["doc_id"] is None else texts[r["doc_id"]]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]) == brute(text), text
        assert set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(",")) and 0 <= r["score"] <= 1


def test_rules_find_and_suppress(spark):
    assert 200 <= len(rules()) <= 500
    for _, _, keyword, pattern, priority in rules():
        re.compile(pattern)
        assert keyword and priority in (1, 2, 3)
    docs = spark.createDataFrame([
        (0, "Licensed under the Apache License, Version 2.0."), (1, "released under GNU Lesser General Public License v2.1 or later"), (2, "SPDX-License-Identifier: MPL-2.0"),
        (3, "Permission is hereby granted, free of charge, to any person obtaining a copy"), (4, "Licensed under CC BY-NC 4.0."), (5, "nothing to see here"), (6, "all rights reserved")], "doc_id long, text string")
    got = {r["doc_id"]: r for r in license_scan(docs).collect()}
    assert [got[i]["labels"] for i in range(7)] == ["apache", "lgpl", "mpl", "mit", "cc-by,cc-by-nc", "", "proprietary"]
    assert got[0]["score"] == 1.0 and got[5]["score"] == 0.0 and got[6]["score"] == 0.5
    rows, detections = scan(docs)
    one = detections.join(rows, "_row").where("doc_id = 0").collect()
    assert len(one) == 1 and (one[0]["first"], one[0]["last"], one[0]["priority"]) == (0, 7, 3)  # the shorter ones lie within it


def test_suppression_equals_all_pairs(spark):
    rng = random.Random(5)
    bits = ["licensed under the", "apache license version 2 0", "gpl v3", "gnu general public license version 3 or later", "mit license", "bsd 3 clause", "cc by 4 0", "x", "all rights reserved", "mozilla public license 2 0"]
    docs = spark.createDataFrame([(i, " ".join(rng.choice(bits) for _ in range(12))) for i in range(60)], "doc_id long, text string")
    rows, detections = scan(docs)
    texts = {r["_row"]: r["norm"] for r in rows.collect()}
    got = {}
    for r in detections.collect():
        got.setdefault(r["_row"], set()).add((r["rule"], r["first"], r["last"]))
    for row, norm in texts.items():
        found = []
        for rule, _, keyword, pattern, priority in rules():
            if keyword in norm:
                for m in re.finditer(rf"(?<![^ ])(?:{pattern})(?![^ ])", norm):
                    first = len(norm[: m.start()].split())
                    found.append((rule, first, first + len(m[0].split()) - 1, priority))
        key = lambda d: (d[1], -d[2], -d[3], d[0])
        keep = {d[:3] for d in found if not any(e != d and e[3] >= d[3] and e[1] <= d[1] and e[2] >= d[2] and key(e) < key(d) for e in found)}
        assert got.get(row, set()) == keep


def matches(parsed, branch, most):
    """A text that a parsed pattern matches, with one choice of alternatives and the least or greatest number of repeats."""
    out = ""
    for op, av in parsed:
        op = str(op)
        if op == "LITERAL":
            out += chr(av)
        elif op == "ANY":
            out += "x"
        elif op == "IN":
            kind, value = av[0]
            out += {"LITERAL": lambda v: chr(v), "RANGE": lambda v: chr(v[0]), "CATEGORY": lambda v: "a"}[str(kind)](value)
        elif op == "BRANCH":
            out += matches(av[1][branch % len(av[1])], branch, most)
        elif op == "SUBPATTERN":
            out += matches(av[3], branch, most)
        else:
            low, high, inner = av
            out += matches(inner, branch, most) * (min(high, low + 3) if most else low)
    return out


def test_no_rule_is_gated_out(spark):
    texts, wanted = [], []
    for rule, label, keyword, pattern, _ in rules():
        for branch in (0, 1, 2, 3, -1):
            for most in (False, True):
                text = matches(re._parser.parse(pattern), branch, most)
                assert re.fullmatch(pattern, text), (pattern, text)
                text = text if keyword in text else f"{text} {keyword}"
                texts += [text, "\n".join(text.upper().split()), f"x-{'  '.join(text.title().split())}."]
                wanted += [(rule, label)] * 3
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    shut = docs.selectExpr("doc_id", "lower(text) AS low").where(~gated(F.col("low"))).collect()
    assert not [(wanted[r["doc_id"]], r["low"]) for r in shut]


def test_short_names_are_found(spark):
    wanted = {"released under the MPL 2.0": "mpl", "available under the EPL v1.0": "epl", "CDDL-1.1": "cddl", "EUPLv1.2": "eupl", "Creative\nCommons Attribution 4.0": "cc-by", "the same\nterms  as Perl itself": "perl"}
    docs = spark.createDataFrame(list(enumerate(wanted)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in license_scan(docs).collect()}
    for i, label in enumerate(wanted.values()):
        assert label in got[i]["labels"].split(",") and got[i]["score"] > 0
