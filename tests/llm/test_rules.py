"""Repetition coverage, the rule ensemble, license scans and preference pairs against brute force."""

import re
import zlib
from collections import Counter

import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from deltahop.llm import license_scan, preference, quality_rules, repetition
from deltahop.llm import textnum as tn

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(text):
    text = text or ""
    words = WORD.findall(text)
    out = {"n_words": len(words), "word_chars": sum(map(len, words)), "n_symbols": len(re.findall(r"[#*$%&|<>]", text))}
    seen, dup = set(), 0
    for line in text.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    out["n_dup_lines"] = dup

    def covered(n):
        grams = Counter(tuple(words[i : i + n]) for i in range(len(words) - n + 1))
        hit = set()
        for i in range(len(words) - n + 1):
            if grams[tuple(words[i : i + n])] > 1:
                hit.update(range(i, i + n))
        return hit

    out["n_repeat_words"] = len(covered(5))
    for n in (5, 7, 10):
        out[f"coverage_{n}"] = round(sum(len(words[i]) for i in covered(n)) / max(1, out["word_chars"]), 9)
    return out


def measured(texts):
    raw = [(t or "").encode() for t in texts]
    offsets = np.concatenate([[0], np.cumsum([len(r) for r in raw])]).astype(np.int64)
    return repetition.measure(np.frombuffer(b"".join(raw), np.uint8), offsets, repetition.RepetitionRules())


@settings(max_examples=60, deadline=None)
@given(st.lists(st.text(alphabet="ab é\n#", max_size=80), max_size=5))
def test_repetition_measures_match_brute_force(texts):
    got = measured(texts)
    for k, text in enumerate(texts):
        for name, value in brute(text).items():
            assert round(float(got[name][k]), 9) == value, (name, text)


def test_repetition_on_odd_rows(spark, odd_docs):
    rows = repetition.repetition_coverage(odd_docs).collect()
    assert len(rows) == odd_docs.count()
    by = {r.doc_id: r for r in rows}
    assert by[2].n_words == 0 and by[2].base_failed and not by[2].kept
    assert by[5].base_failed and not by[5].kept
    assert by[7].kept and by[1].kept
    assert by[6].n_dup_lines == 1
    assert repetition.repetition_coverage(odd_docs.limit(0)).collect() == []


def test_longer_repeats_are_allowed_less():
    text = lambda n, m: " ".join([f"r{i:03}" for i in range(n)] * 2 + [f"w{i:03}" for i in range(m)])
    texts = [text(6, 88), text(9, 114), text(10, 178), text(12, 178), text(5, 54)]
    got = measured(texts)
    limits = repetition.RepetitionRules().duplicated
    failed = [{n for n in limits if got[f"coverage_{n}"][k] > limits[n]} for k in range(len(texts))]
    assert failed == [set(), {7, 8, 9}, {10}, {9, 10}, {5}]
    assert got["kept"].tolist() == [True, False, False, False, False]
    assert not got["base_failed"].any()


def test_word_hash_does_not_depend_on_place():
    raw = "Same same x\nsame Same".encode()
    w = tn.Words(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]))
    assert w.hash[0] == w.hash[4] and w.hash[1] == w.hash[3] and w.hash[0] != w.hash[1]
    low = tn.Words(np.frombuffer(raw, np.uint8), np.array([0, len(raw)]), lower=True)
    assert len(set(low.hash[[0, 1, 3, 4]].tolist())) == 1


def test_rule_columns_equal_numpy_scores_and_learn(spark):
    rng = np.random.default_rng(3)
    good = [" ".join(f"w{rng.integers(500)}" for _ in range(rng.integers(20, 200))) for _ in range(300)]
    bad = [" ".join(f"w{rng.integers(500)}###" for _ in range(rng.integers(20, 200))) for _ in range(100)]
    rows = [(i, t) for i, t in enumerate(good + bad)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    labels = spark.createDataFrame([(i, int(i < 300)) for i, _ in rows], "doc_id bigint, quality int")
    model = quality_rules.fit(docs, labels)
    assert model.rules
    out = quality_rules.score_documents(docs, model).toPandas().set_index("doc_id")
    stats = quality_rules.with_statistics(docs).toPandas().set_index("doc_id")
    x = np.array([[r[s] for s in quality_rules.STATISTICS] for r in stats["stats"]])
    assert np.allclose(model.predict(x), out.loc[stats.index, "score"], atol=1e-8)
    test = [i for i, _ in rows if zlib.crc32(str(i).encode()) % 4 == 2]
    assert np.mean([(out.loc[i, "predicted"] == 1) == (i < 300) for i in test]) > 0.97


def test_lasso_meets_its_optimality_conditions():
    rng = np.random.default_rng(4)
    z = (rng.random((400, 12)) < rng.uniform(0.1, 0.9, 12)).astype(float)
    y = (rng.random(400) < 1 / (1 + np.exp(-(2.5 * z[:, 0] - 2 * z[:, 1] + 0.3)))).astype(float)
    for penalty in (0.005, 0.03, 10.0):
        b, w = quality_rules.lasso_logistic(z, y, penalty, steps=4000)
        left = 1 / (1 + np.exp(-(b + z @ w))) - y
        slope = ((z - z.mean(0)) / np.maximum(z.std(0), 1e-3)).T @ left / len(y)
        assert abs(left.mean()) < 1e-4  # the intercept is free
        assert np.all(np.abs(slope) <= penalty + 1e-4)
        on = w != 0
        assert np.allclose(slope[on], -penalty * np.sign(w[on]), atol=1e-4)
        assert on[:2].all() if penalty < 1 else not on.any()


def test_first_tree_splits_as_an_exhaustive_search_does():
    rng = np.random.default_rng(6)
    x = np.round(rng.random((60, len(quality_rules.STATISTICS))), 2)
    y = (x[:, 3] + 0.3 * x[:, 7] + rng.normal(0, 0.1, 60) > 0.7).astype(float)
    rules = quality_rules.extract_rules(x, y, trees=1, depth=2, n_bins=200, least=5)
    p = (y.sum() + 1) / (len(y) + 2)
    grad, hess = y - p, np.full(60, p * (1 - p))

    def best(rows):
        found = (1e-6, None)
        for k in range(x.shape[1]):
            for cut in np.unique(np.quantile(x[:, k], np.linspace(0, 1, 201)[1:-1])):
                low = rows[x[rows, k] <= cut]
                high = np.setdiff1d(rows, low)
                if min(len(low), len(high)) >= 5:
                    gain = sum(grad[s].sum() ** 2 / (hess[s].sum() + 1) for s in (low, high)) - grad[rows].sum() ** 2 / (hess[rows].sum() + 1)
                    if gain > found[0] + 1e-12:
                        found = (gain, (k, cut, low, high))
        return found[1]

    k, cut, low, high = best(np.arange(60))
    want = set()
    for rows, above in ((low, False), (high, True)):
        path = ((quality_rules.STATISTICS[k], float(cut), above),)
        want.add(path)
        inner = best(rows) if len(rows) >= 10 else None
        if inner:
            want |= {(*path, (quality_rules.STATISTICS[inner[0]], float(inner[1]), side)) for side in (False, True)}
    assert {r.conditions for r in rules} == want


def test_rule_ensemble_on_odd_rows(spark, odd_docs):
    labels = spark.createDataFrame([(1, 1), (1, 0), (5, 0), (None, 1)], "doc_id bigint, quality int")
    model = quality_rules.fit(odd_docs, labels)
    rows = quality_rules.score_documents(odd_docs, model).collect()
    assert len(rows) == odd_docs.count() and all(0 <= r.score <= 1 for r in rows)
    empty = quality_rules.fit(odd_docs, labels.limit(0))
    assert quality_rules.score_documents(odd_docs.limit(0), empty).collect() == []


def test_license_rules_in_order_and_wrapped(spark):
    s = license_scan.SENTENCES
    apache = "Licensed under the Apache License, Version 2.0 (the \"License\");\nyou may not use this file except in\ncompliance with the License.\nYou may obtain a copy of the License at\n\nUnless required by applicable law or agreed to in writing, software\ndistributed under the License is distributed on an \"AS IS\" BASIS,\nWITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.\nSee the License for the specific language governing permissions and\nlimitations under the License."
    rows = [(1, apache), (2, "Prose here.\nReleased under the MIT License.\nMore."), (3, None), (4, ""), (5, ". ".join([s["mit_liability"], s["mit_grant"]]) + "."), (2, "x")]
    out = {(r.doc_id, r.rule) for r in license_scan.scan_licenses(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()}
    assert out == {(1, "apache-notice"), (2, "mit-line")}


MIT = """Copyright (c) 2020 Some Body

Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE
SOFTWARE."""
APACHE = """Copyright 2020 Some Body

Licensed under the Apache License, Version 2.0 (the "License");
you may not use this file except in compliance with the License.
You may obtain a copy of the License at

    http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software
distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
See the License for the specific language governing permissions and
limitations under the License."""
GPL = """This program is free software: you can redistribute it and/or modify
it under the terms of the GNU General Public License as published by
the Free Software Foundation, either version 3 of the License, or
(at your option) any later version.

This program is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the
GNU General Public License for more details."""
BSD = """Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution.

THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND
ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED
WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE
DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER BE LIABLE."""


def test_licenses_as_they_are_wrapped_and_commented(spark):
    texts = {"MIT": MIT, "Apache-2.0": APACHE, "GPL-3.0-or-later": GPL, "BSD-2-Clause": BSD}
    commented = [lambda t: t, lambda t: t.replace("\n", "\r\n")]
    commented += [lambda t, mark=mark: "\n".join(f"{mark} {line}".rstrip() for line in t.split("\n")) for mark in ("#", "//", " *", ";;", "   ")]
    rows = [(10 * k + i, f(t)) for k, t in enumerate(texts.values()) for i, f in enumerate(commented)]
    more = ["This file is licensed under the MIT License.", "A line\nReleased under the MIT License\nCopyright", "We like the MIT License.", "Released under the MIT\n\nLicense.", "Prose\nMIT License\nCopyright"]
    rows += [(100 + i, t) for i, t in enumerate(more)]
    found = license_scan.scan_licenses(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    want = {(10 * k + i, name) for k, name in enumerate(texts) for i in range(len(commented))}
    assert {(r.doc_id, r.license) for r in found if r.doc_id < 100} == want
    assert {(r.doc_id, r.rule, r.first_pos) for r in found if r.doc_id >= 100} == {(100, "mit-licensed-line", 0), (101, "mit-line", 1), (104, "mit-title-short", 1)}


MORE = {
    "LGPL-2.1-or-later": GPL.replace("This program", "This library").replace("GNU General", "GNU Lesser General").replace("version 3", "version 2.1"),
    "AGPL-3.0-or-later": GPL.replace("GNU General", "GNU Affero General"),
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public\nLicense, v. 2.0. If a copy of the MPL was not distributed with this\nfile, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "ISC": """Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES
WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF
MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR
ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES
WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN
ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF
OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "Unlicense": """This is free and unencumbered software released into the public domain.

Anyone is free to copy, modify, publish, use, compile, sell, or
distribute this software, either in source code form or as a compiled
binary, for any purpose, commercial or non-commercial, and by any
means.""",
    "Zlib": """This software is provided 'as-is', without any express or implied
warranty.  In no event will the authors be held liable for any damages
arising from the use of this software.

Permission is granted to anyone to use this software for any purpose,
including commercial applications, and to alter it and redistribute it
freely, subject to the following restrictions:""",
    "GPL-3.0-only": "x = 1\n# SPDX-License-Identifier: GPL-3.0-only\ny = 2",
    "CC-BY-SA-4.0": "This work is licensed under a Creative Commons\nAttribution-ShareAlike 4.0 International License.",
}


def test_more_licenses_as_published(spark):
    rows = [(2 * k + i, t if i == 0 else "\n".join(f"// {line}" for line in t.split("\n"))) for k, t in enumerate(MORE.values()) for i in (0, 1)]
    found = license_scan.scan_licenses(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()
    assert {(r.doc_id, r.license) for r in found} == {(2 * k + i, name) for k, name in enumerate(MORE) for i in (0, 1)}
    assert len(license_scan.RULES) >= 60 and all(set(steps) <= set(license_scan.SENTENCES) for _, steps in license_scan.RULES.values())


def test_license_scan_on_odd_rows(spark, odd_docs):
    halves = MIT.split("IN NO EVENT")
    rows = [(1, halves[0]), (1, "IN NO EVENT" + halves[1]), (2, "filler words here\n" * 20000 + MIT), (3, None), (4, ""), (None, MIT), (2, "filler words here\n" * 20000 + MIT)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").selectExpr("*", "'x' AS row_key", "'y' AS line", "1 AS pos")
    found = license_scan.scan_licenses(docs).collect()
    assert sorted((r.doc_id is None, r.doc_id, r.rule) for r in found) == [(False, 2, "mit-text")] * 2 + [(True, None, "mit-text")]
    assert license_scan.scan_licenses(odd_docs.limit(0)).collect() == []


def test_prefixes_of_random_pairs(spark):
    rng = np.random.default_rng(5)
    side = lambda n: [(("user", "assistant")[int(rng.integers(2))], "ab"[int(rng.integers(2))]) for _ in range(n)]
    rows = []
    for k in range(200):
        a, b = side(int(rng.integers(0, 6))), side(int(rng.integers(0, 6)))
        if k % 3 == 0:
            b = a[: int(rng.integers(0, 6))] + b
        rows.append((k, None if k % 41 == 5 else a, None if k % 37 == 7 else b))
    turn = "array<struct<role: string, text: string>>"
    out = {r.pair_id: r for r in preference.format_preferences(spark.createDataFrame(rows, f"pair_id bigint, chosen {turn}, rejected {turn}")).collect()}
    show = lambda turns: "".join(f"<|im_start|>{r}\n{t}<|im_end|>\n" for r, t in turns)
    for k, a, b in rows:
        r, a_, b_ = out[k], a or [], b or []
        n = next((i for i, (x, y) in enumerate(zip(a_, b_, strict=False)) if x != y), min(len(a_), len(b_)))
        assert (r.n_prefix, r.prompt, r.chosen_completion, r.rejected_completion) == (n, show(a_[:n]), show(a_[n:]), show(b_[n:]))
        assert r.complete == (a is not None and b is not None) and r.differs == (a_ != b_)
        for text, spans, turns in ((r.chosen_completion, r.chosen_spans, a_[n:]), (r.rejected_completion, r.rejected_spans, b_[n:])):
            assert [text[s.start : s.end] for s in spans] == [f"{t}<|im_end|>\n" for role, t in turns if role == "assistant"]


def test_preference_prefix_and_masks(spark):
    turns = [(0, 0, "user", "hi"), (0, 1, "assistant", "yo"), (1, 0, "user", "hi"), (1, 1, "assistant", "other"), (2, 0, None, None), (None, 0, "user", "x"), (None, 0, "assistant", "x"), (4, 0, "assistant", "same"), (5, 0, "assistant", "same")]
    df = spark.createDataFrame(turns, "conv_id bigint, turn bigint, role string, text string")
    rows = {r.pair_id: r for r in preference.preference_digest(df).collect()}
    r = rows[0]
    assert r.n_prefix == 1 and r.prompt == "<|im_start|>user\nhi<|im_end|>\n" and r.differs and r.complete
    a, b = map(int, r.chosen_spans.split("-"))
    assert r.chosen_completion[a:b] == "yo<|im_end|>\n"
    a, b = map(int, r.rejected_spans.split("-"))
    assert r.rejected_completion[a:b] == "other<|im_end|>\n"
    assert not rows[4].differs and rows[4].n_prefix == 1 and rows[4].chosen_completion == ""
    assert not rows[2].complete and not rows[None].complete
    assert preference.preference_digest(df).where("pair_id is null").count() == 2
    assert preference.preference_digest(df.limit(0)).collect() == []
