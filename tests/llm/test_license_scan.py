import random
import re

from pyspark.sql import functions as F

from planegrid.llm import license_scan
from planegrid.llm.registry import op5_license_scan
from tests.conftest import SF


def plain(text):
    return re.findall(r"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def brute(text, containment=0.8):
    """All windows of all templates, nothing hashed."""
    w, out = plain(text), []
    pairs = list(zip(w, w[1:]))
    for name, template in license_scan.TEXTS.items():
        t = plain(template)
        wanted, size, best = set(zip(t, t[1:])), license_scan.window_of(len(t)), None
        for at in range(len(w)):
            window = pairs[at : at + size - 1]
            inside = [i for i, p in enumerate(window) if p in wanted]
            held = len({window[i] for i in inside}) / len(wanted)
            if held >= containment:
                new = (at + inside[0], at + inside[-1] + 2, name, held)
                if best and new[0] < best[1]:
                    best = new if held > best[3] else best
                else:
                    out += [best] if best else []
                    best = new
        out += [best] if best else []
    return sorted(out)


def test_bands_reach_the_chance():
    for n in (2, 3, 7, 12, 40):
        shingles, inside = n - 1, license_scan.window_of(n) - 1
        likeness = 0.8 * shingles / (inside + 0.2 * shingles)
        assert (1 - likeness) ** license_scan.bands_for(n, 0.8, 1e-5) <= 1e-5


def test_whole_table(spark):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    got = op5_license_scan(spark, SF).collect()
    assert len(got) == len(texts) and sum(r.n_matches for r in got) > 0
    for r in got:
        want = brute(texts[r.doc_id])
        assert r.matches == ",".join(f"{name}:{a}:{b}" for a, b, name, _ in want) and r.n_matches == len(want)
        assert r.licenses == ",".join(sorted({x[2] for x in want}))


def test_edited_and_odd_texts(spark):
    rnd = random.Random(2)
    rows = [(None, None), (1, ""), (1, "All rights"), (2, "ALL -- rights... reserved"), (2, "all rights reserved " * 3), (3, "é " * 50_000 + license_scan.TEXTS["MIT"])]
    for k, t in enumerate(license_scan.TEXTS.values()):
        w = t.split()
        w[rnd.randrange(len(w))] = "edited"
        rows.append((10 + k, f"some words before {' '.join(w)} and some after"))
    df = spark.createDataFrame(rows, "doc_id long, text string").select("*", F.lit(1).alias("matches"))
    got = license_scan.scan(df).collect()
    key = lambda r: (repr(r[0]), r[1])
    assert sorted(((r.doc_id, [(m.first_word, m.stop_word, m.license, m.containment) for m in r.matches]) for r in got), key=key) == sorted(((k, brute(t)) for k, t in rows), key=key)
    assert license_scan.scan(df.limit(0)).count() == 0


def test_common_notices_are_found(spark):
    texts = {
        "BSD": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1.",
        "ISC": "Permission to use, copy, modify, and distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
        "MPL-2.0": "# This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy",
        "LGPL": "it under the terms of the GNU Lesser General Public License as published",
        "GPL-header": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    }
    got = license_scan.scan(spark.createDataFrame(list(texts.items()), "doc_id string, text string")).collect()
    assert {r.doc_id: [m.license for m in r.matches] for r in got} == {k: [k] for k in texts}


def test_whole_texts_and_low_containment(spark):
    """Bands follow from the containment asked for, however many that takes."""
    text = " ".join(license_scan.TEXTS["MIT-text"].split()[:90])
    assert license_scan.bands_for(170, 0.1, 1e-5) > 64
    df = spark.createDataFrame([(1, "x " * 50 + text + " y" * 50), (2, "nothing of the kind " * 40)], "doc_id int, text string")
    got = {r.doc_id: {m.license for m in r.matches} for r in license_scan.scan(df, {"MIT-text": license_scan.TEXTS["MIT-text"]}, containment=0.1).collect()}
    assert got == {1: {"MIT-text"}, 2: set()}
    whole = spark.createDataFrame([(k, f"Copyright 2020 A. N. Author\n{t}\nint main;") for k, t in license_scan.TEXTS.items()], "doc_id string, text string")
    assert all(r.doc_id in {m.license for m in r.matches} for r in license_scan.scan(whole).collect())
