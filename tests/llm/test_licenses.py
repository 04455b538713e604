"""License rules on labelled lines, against brute force, and on long texts."""

from __future__ import annotations

import random
import time

import pytest

from tracegraph.llm import license_pack
from tracegraph.llm import license_rules as lic

LABELLED = [
    ("licensed under GPLv2", "gpl-2.0"),
    ("GPL-3.0", "gpl-3.0"),
    ("SPDX-License-Identifier: GPL-2.0-only", "gpl-2.0-only"),
    ("redistribute it under LGPL v3", "lgpl-3.0"),
    ("either version 2 of the License", None),
    ("Licensed under the Apache License, Version 2.0 (the \"License\")", "apache-2.0"),
    ("http://www.apache.org/licenses/LICENSE-2.0", "apache-2.0"),
    ("Released under the MIT License.", "mit"),
    ("Permission is hereby granted, free of charge, to any person obtaining a copy of this software", "mit"),
    ("Redistribution and use in source and binary forms, with or without modification, are permitted", "bsd"),
    ("BSD-3-Clause", "bsd-3-clause"),
    ("GNU Affero General Public License v3", "agpl-3.0"),
    ("GNU Lesser General Public License version 2.1", "lgpl-2.1"),
    ("Mozilla Public License 2.0", "mpl-2.0"),
    ("MPL-2.0", "mpl-2.0"),
    ("Eclipse Public License - v 2.0", None),
    ("CC BY-NC-SA 4.0", "cc-by-nc-sa-4.0"),
    ("https://creativecommons.org/licenses/by-sa/4.0/", "cc-by-sa"),
    ("CC0 1.0 Universal", "cc0"),
    ("This is free and unencumbered software released into the public domain.", "unlicense"),
    ("Boost Software License, Version 1.0", "boost-1.0"),
    ("Copyright (c) 2019-2021", "copyright"),
    ("Tous droits réservés", "reserved"),
    ("er kam mit dem Zug und isst gern", None),
    ("we went by cc mail apache helicopters over eclipse", None),
]


@pytest.mark.parametrize("text,label", LABELLED)
def test_labelled_lines(text, label):
    found = lic.scan_text(text)[5].split(",")
    if label:
        assert label in found
    elif not lic.scan_text(text)[4]:
        assert not {"gpl", "mit", "apache", "isc"} & set(found)


def test_rules_are_many_distinct_and_hold_their_keyword():
    rules = license_pack.lines()
    assert len(rules) >= 200 and len({e for *_, e in rules}) == len(rules)
    texts = [t for t, label in LABELLED if label]
    for text in texts:  # a match without the keyword would be lost by the prefilter
        words = lic.normalised(text)
        for r in lic.rules():
            if r.pattern.search(words):
                assert r.keyword.encode() in words, (r.keyword, text)


def _brute(words: bytes) -> list:
    """Every rule on every text, without prefilter; containment by comparing all kept intervals."""
    hits = []
    for i, r in enumerate(lic.rules()):
        for m in r.pattern.finditer(words):
            first = words[: m.start()].count(b" ")
            hits.append((i, first, first + m.group().count(b" ") - 1))
    kept = []
    for i, a, z in sorted(hits, key=lambda h: (-lic.rules()[h[0]].confidence, h[1] - h[2], h[0], h[1])):
        if not any(x <= a and z <= y for x, y, *_ in kept):
            kept.append((a, z, lic.rules()[i].label, lic.rules()[i].confidence))
    return sorted(kept)


def test_against_brute_force():
    rnd = random.Random(3)
    parts = [t for t, _ in LABELLED] + ["plain words here", "or any later version", "only", "license", "2.0"]
    for _ in range(150):
        words = lic.normalised(" ".join(rnd.choices(parts, k=rnd.randint(1, 12))))
        assert lic.detect(words, lic._spaces(words)) == _brute(words)


def test_time_is_in_proportion_to_the_text():
    line = "Licensed under the Apache License, Version 2.0. All rights reserved. GNU General Public License v3 CC BY 4.0\n"
    spent = []
    for n in (2_000, 16_000):
        t = time.perf_counter()
        row = lic.scan_text(line * n)
        spent.append(time.perf_counter() - t)
        assert row[1] == 3 * n
    assert spent[1] < 24 * spent[0]
    assert spent[1] < 20
