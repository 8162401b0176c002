"""Gates and keywords of the license scan lose nothing."""

import random
import re
from re import _constants as kind
from re import _parser as parser

from pyspark.sql import functions as F

from levcut.llm import licenses

PHRASES = [
    "released into the public domain", "it is in the public domain", "All rights reserved", "without warranties of any kind",
    "This program is free software; you can redistribute it and/or modify it", "distributed under the terms of the MIT", "under the terms in MIT",
    "Permission is hereby granted, free of charge, to any person obtaining a copy", "Permission to use, copy, modify, and/or distribute this software for any purpose",
    "Redistribution and use in source and binary forms, with or without modification", "available under the GNU General Public License version 3",
    "governed by the terms of the lesser general public license v2.1", "distributed under Creative Commons Attribution 4.0", "published under cc by-sa 4.0",
    "published under cc+by", "provided under creative commons zero", "distributed under do what the f*** you want to public license",
    "the common development and distribution license", "the open data commons open database license", "the universal permissive license",
    "the academic free license", "gnu free documentation license", "python software foundation license", "proprietary and confidential. Do not copy",
    "This is free and unencumbered software released into the public domain", "nothing of the kind",
]


def instance(parsed, rng):
    """A random string of a parsed pattern."""
    out = ""
    for op, value in parsed:
        if op is kind.LITERAL:
            out += chr(value)
        elif op is kind.IN:
            op_, what = rng.choice(value)
            out += chr(what) if op_ is kind.LITERAL else chr(rng.randint(*what)) if op_ is kind.RANGE else "7"
        elif op is kind.ANY:
            out += "x"
        elif op is kind.BRANCH:
            out += instance(rng.choice(value[1]), rng)
        elif op is kind.SUBPATTERN:
            out += instance(value[3], rng)
        elif op in (kind.MAX_REPEAT, kind.MIN_REPEAT):
            out += "".join(instance(value[2], rng) for _ in range(rng.randint(value[0], min(value[1], value[0] + 2))))
    return out


def test_every_match_holds_a_keyword_and_every_keyword_a_gate():
    rng = random.Random(5)
    assert len(licenses.rules()) > 400 and len(licenses.SIGNATURES) > 160
    for label, pattern, keywords, _, _ in licenses.rules():
        assert keywords, pattern
        assert all(any(g in k for g in licenses.gates()) for k in keywords), label
        for _ in range(30):
            text = instance(parser.parse(pattern), rng)
            match = re.search(pattern, text)
            assert match is None or any(k in match[0] for k in keywords), (pattern, text)


def test_every_rule_is_found_in_wrapped_text(spark):
    rng = random.Random(6)
    made = []
    for i, (_, pattern, _, _, _) in enumerate(licenses.rules()):
        for _ in range(4):
            text = instance(parser.parse(pattern), rng)
            if re.search(pattern, re.sub(" +", " ", text)):
                made.append((i, re.sub(" ", lambda _: rng.choice([" ", "\n", "  ", " \t\r\n"]), text.upper() if "é" not in text else text)))
    docs = spark.createDataFrame(list(enumerate(t for _, t in made)), "doc_id long, text string").repartition(4)
    found = {r["doc_id"]: r for r in licenses.scan(docs).collect()}
    ordered = licenses.rules()
    for k, (i, _) in enumerate(made):
        label, _, _, priority, _ = ordered[i]
        # The rule's own label, or one that outranks it on the same words.
        assert any(d["label"] == label or d["priority"] >= priority for d in found[k]["detections"]), (ordered[i], made[k])


def plain_scan(text):
    """Detections by trying every rule, suppression by comparing all pairs."""
    folded = re.sub(r"\s+", " ", text.lower())
    found = [(m.start(), m.end(), p, i, a) for i, (a, b, _, p, _) in enumerate(licenses.rules()) for m in re.finditer(b, folded, re.A)]

    def over(a, b):
        longer = a[1] - a[0] > b[1] - b[0]
        return a[0] <= b[0] and a[1] >= b[1] and (a[2] > b[2] or a[2] == b[2] and (longer or a[3] < b[3]))

    return sorted(b for b in found if not any(over(a, b) for a in found))


def test_scan_equals_the_plain_one(spark):
    rng = random.Random(7)
    texts = [p.replace(" ", gap) for p in PHRASES for gap in (" ", "\n", "  ", " \t\r\n")]
    texts += [" ".join(rng.choice(PHRASES + ["Copyright 2001", "(c) 1999-2004 x", "licensed under MIT", "bsd+2+clause"]) for _ in range(12)) for _ in range(40)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    for r in licenses.scan(docs).collect():
        assert sorted((d["start"], d["end"], d["priority"], d["id"], d["label"]) for d in r["detections"]) == plain_scan(texts[r["doc_id"]])
    assert not plain_scan("bsd+2+clause")


def test_many_hits_in_one_text(spark):
    text = "licensed under MIT, Copyright 2001; " * 3000
    r = licenses.scan(spark.range(1).select(F.col("id").alias("doc_id"), F.lit(text).alias("text"))).first()
    assert len(r["detections"]) == 6000 and r["labels"] == "copyright-notice,mit"
