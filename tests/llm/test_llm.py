"""Training-data operators: worked cases, edge cases and brute force on small tables."""

import hashlib
import itertools
import random
import re
import zlib

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from metricsearch.llm import chat, components, imatch, langid, licences, main_text, maxscore, mixing, ngram_join, packing, queries, scratch, token_file, tokens, words

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(s):
    return re.sub("[A-Z]", lambda m: m[0].lower(), s or "")


def shingles(text):
    w = WORD.findall(lower(text))
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def table(spark, rows):
    return spark.createDataFrame([(i, t, lang, src, len(t or "")) for i, t, lang, src in rows], DOCS)


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in every column, empty and blank texts, ties, repeated rows, a very long text, extra columns."""
    rng = random.Random(5)
    long = " ".join(rng.choice(["alpha", "beta", "gamma", "delta", "eps"]) + str(rng.randrange(400)) for _ in range(30_000))
    base = " ".join(f"w{i}" for i in range(60))
    rows = [(1, base, "en", "a"), (2, base, "en", "a"), (2, base, "en", "a"), (3, base + " tail", None, "b"), (4, None, "de", None), (5, "", None, "b"), (6, " \t\n", "en", "a"), (7, "one two", "en", None), (8, "One TWO", "en", None), (None, base, "en", "a"), (9, long, "en", "c"), (10, "ein haus und der garten für die leute", "de", "c"), (11, "the house and the garden of people", "en", "c"), (12, "12 34 !!", None, "b")]
    return table(spark, rows).withColumn("size_", F.lit(1)).withColumn("text_", F.lit("x"))


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


# 1


def test_main_text_of_an_article():
    page = '<html><head><title>t</title><script>var a="</p>";</script></head><body><nav><a href="/x">menu</a></nav><div class="ad">Buy this now.</div><article><h1>Head</h1><p><b>First &amp; best<br><p>A.<aside>side</aside><p>Last   line</p><div class="comments"><p>nice post</p></div></article><footer>&copy; us</footer>'
    assert main_text.main_text(page) == "Head\n\nFirst & best\n\nA.\n\nLast line"


def test_main_text_without_an_article():
    body = "".join(f"<p>{'Words of the story number %d go on and on. ' % i * 3}</p>" for i in range(5))
    page = f"<body><ul><li><a href=a>Home</a></li><li><a href=b>News</a></li></ul><div id=content>{body}<p>Short.</p><p>{'And the end of the story is here at last. ' * 3}</p></div><div class='sidebar'><p>{'Other stories you may like are here. ' * 4}</p></div></body>"
    lines = main_text.main_text(page).split("\n\n")
    assert len(lines) == 7 and lines[5] == "Short." and "Home" not in lines and "Other" not in " ".join(lines)


def test_main_text_around_adverts():
    long = "Words of the story go on and on until the end of the line is reached at last. " * 2
    ad = "<div class='{}'>Buy this now.</div>"
    share, advert = ad.format("share"), ad.format("ad")
    says = lambda page: main_text.main_text(page).split("\n\n")
    two = [long.strip()] * 2
    body = f"<p>{long}</p><p>{long}</p>"
    for open_, close in (("<body>", "</body>"), ("<body><div id=content>", "</div></body>")):
        assert says(f"{open_}<h1>A title</h1>{share}{body}{close}") == ["A title", *two]
        assert says(f"{open_}{body}{advert}<p>Short last line.</p>{close}") == [*two, "Short last line."]
        assert says(f"{open_}{body}{advert}<p>Short.</p>{advert}{body}{close}") == [*two, "Short.", *two]
        assert says(f"{open_}{body}{advert}<p>See <a href=x>all of the other stories</a></p>{close}") == [*two, "See all of the other stories"]
    assert says(f"<div id=content><h1>A title</h1>{share}<div class=text>{body}</div></div>") == ["A title", *two]
    menu = "<ul><li><a href=a>Home</a></li><li>News</li></ul>"
    assert says(f"<body>{menu}{advert}<div id=content>{body}</div>{advert}<div id=x>Imprint</div></body>") == two


def test_main_text_hints_are_whole_names():
    body = f"<p>{'Words of the story go on and on until the end of the line. ' * 3}</p>"
    for name in ("content with-sidebar", "content no-ads", "has-share", "post no-comments", "sidebar-layout", "content-with-sidebar", "noticeable"):
        for element in ("div", "article"):
            assert main_text.main_text(f"<{element} class='{name}'>{body}</{element}>"), name
    for name in ("sidebar", "left-sidebar", "ad-slot", "ad_box_2", "x social-share", "page-header", "skip-link", "sign-up", "comments-area", "share-buttons", "cookie-notice"):
        assert main_text.main_text(f"{body}<div class='{name}'>{body.replace('story', 'other')}</div>").count("other") == 0, name


def test_main_text_hints_on_lines_and_inline():
    body = f"<p>{'Words of the story go on and on until the end of the line. ' * 3}</p>"
    says = lambda page: main_text.main_text(page).split("\n\n")
    two = [" ".join(body[3:-4].split())] * 2
    for lost in ("<p class='advert'>Buy this.</p>", "<p class=advert>Buy this.", "<ul><li class='ad'>Buy this.</ul>", "<table><tr><td class='sidebar'>Buy this.</table>", "<p><span class='ad'>Buy <span>this</span>.</span></p>", "<dl><dd class=ad>Buy this.</dl>", "<p class=ad>Buy <b>this</b> <i>now</p>"):
        assert says(f"<article>{body}{lost}{body}</article>") == two, lost
        assert says(f"<div>{body}{lost}{body}</div>") == two, lost
    assert says(f"<article>{body}<table><tr><td class=ad>Buy<td>A cell.<tr><td>More</table>{body}</article>") == [two[0], "A cell.", "More", two[0]]
    assert says("<article><p>Plain <span class='ad'>Buy</span>words.<ul><li class=menu><ul><li>x</li></ul></li><li>One.</ul></article>") == ["Plain words.", "One."]
    assert "comment" in main_text.main_text(f"<article>{body}<pre>x = 1 <span class=comment># a comment</span></pre></article>")


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 60).map(lambda x: x if x < 45 else 0), max_size=30), st.integers(1, 4), st.integers(1, 120))
def test_surges_and_dives_by_brute_force(weight, window, surge):
    total = lambda i: sum(weight[i : i + window])
    level = min(surge, max([1, *map(total, range(len(weight)))]))
    want, open_ = set(), None
    for i in range(len(weight)):
        if open_ is None and weight[i] and total(i) >= level:
            open_ = i
        if open_ is not None and (total(i) == 0 or i == len(weight) - 1):
            last = max(j for j in range(open_, i + 1) if weight[j])
            want |= set(range(open_, last + 1))
            open_ = None
    assert {i for a, b in main_text.surges(weight, window, surge) for i in range(a, b)} == want


def test_surges_decide_on_given_pages(spark, small):
    pages = [r.html for r in spark.read.parquet(f"{small}/pages.parquet").collect()]
    assert all(any(x[2] for x in main_text.strip_markup(p)) for p in pages if p)  # all declare main text
    texts = {surge: [main_text.main_text(p, surge=surge) for p in pages] for surge in (main_text.SURGE, 2000, 8000)}
    assert texts[main_text.SURGE] != texts[2000] != texts[8000] and all(texts[8000])


@settings(max_examples=60, deadline=None)
@given(st.text(alphabet="<>/ap \"'=!-&;x\n", max_size=80))
def test_main_text_never_fails(page):
    main_text.main_text(page)


def test_main_text_rows(spark, small):
    pages = spark.createDataFrame([(1, "u", None), (1, "u", None), (None, None, ""), (2, "v", "<p>" + "long text here " * 20)], "page_id long, url string, html string").withColumn("text", F.lit("clash"))
    got = main_text.extract(pages).collect()
    assert [r.n_chars for r in got][:3] == [0, 0, 0] and got[3].n_chars == len(got[3].text) > 200
    assert main_text.extract(pages.limit(0)).count() == 0


# 2


def test_licences():
    assert licences.scan_text("Text.\nReleased under the MIT License.\nMore") == (["MIT"], [1], ["mit"])
    assert licences.scan_text("This work is licensed under the GNU General Public License, version 3.")[0] == ["GPL-3.0-only"]
    assert licences.scan_text("Licensed under CC BY-NC 4.0.")[0] == ["CC-BY-NC-4.0"]
    apache = "Licensed under the Apache License, Version 2.0 (the \"License\");\n\nyou may not use this file except in compliance with the License.\nYou may obtain a copy of the License at\n\n http://x.y\n\nUnless required by applicable law or agreed to in writing, software\ndistributed under the License is distributed on an \"AS IS\" BASIS,\nWITHOUT WARRANTIES.\nSee the License for the specific language governing permissions and\nlimitations under the License."
    assert set(licences.scan_text(apache)[0]) == {"Apache-2.0"}
    assert licences.scan_text("SPDX-License-Identifier: GPL-2.0-only")[0] == ["gpl-2.0-only"]
    assert licences.scan_text("A licence to kill is no licence.")[0] == [] and licences.scan_text(None)[0] == []
    for licence, seq in licences.RULES:
        assert all(s in licences.SENTENCES for s in seq), licence


HEADERS = {
    "GPL-2.0-or-later": "Copyright (C) 2020 A. Person\n\nThis program is free software; you can redistribute it and/or modify\nit under the terms of the GNU General Public License as published by\nthe Free Software Foundation; either version 2 of the License, or\n(at your option) any later version.\n\nThis program is distributed in the hope that it will be useful,\nbut WITHOUT ANY WARRANTY; without even the implied warranty of\nMERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the\nGNU General Public License for more details.",
    "LGPL-2.1-or-later": "This library is free software; you can redistribute it and/or\nmodify it under the terms of the GNU Lesser General Public\nLicense as published by the Free Software Foundation; either\nversion 2.1 of the License, or (at your option) any later version.",
    "LGPL-3.0-or-later": "This library is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public\nLicense, v. 2.0. If a copy of the MPL was not distributed with this\nfile, You can obtain one at https://mozilla.org/MPL/2.0/.",
    "MIT": 'Copyright (c) 2020 A. Person\n\nPermission is hereby granted, free of charge, to any person obtaining a copy\nof this software and associated documentation files (the "Software"), to deal\nin the Software without restriction, including without limitation the rights\nto use, copy, modify, and/or sell copies of the\nSoftware, subject to the following conditions:\n\nThe above copyright notice and this permission notice shall be included in all\ncopies or substantial portions of the Software.\n\nTHE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR\nIMPLIED, AND NONINFRINGEMENT. IN NO EVENT SHALL THE\nAUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER\nLIABILITY.',
    "BSD-3-Clause": "Copyright (c) 2020, A. Person\n\nRedistribution and use in source and binary forms, with or without\nmodification, are permitted provided that the following conditions are met:\n\n1. Redistributions of source code must retain the above copyright notice, this\n   list of conditions and the following disclaimer.\n\n2. Redistributions in binary form must reproduce the above copyright notice,\n   this list of conditions and the following disclaimer in the documentation\n   and/or other materials provided with the distribution.\n\n3. Neither the name of the copyright holder nor the names of its\n   contributors may be used to endorse or promote products derived from\n   this software without specific prior written permission.",
}


@pytest.mark.parametrize("lead", ["", "# ", "// ", "* ", " * ", ";; ", "dnl ", "    "])
def test_licence_headers_in_comments(lead):
    for licence, header in HEADERS.items():
        text = "\n".join((lead + line).rstrip() for line in header.split("\n"))
        for whole in (text, f"/*\n{text}\n */\n#include <a.h>\nint main(); x = 1;", text.replace("\n", "\r\n")):
            assert licences.scan_text(whole)[0] == [licence], (licence, whole)
        if licence == "MIT":
            assert licences.scan_text(text)[2] == ["mit-grant", "mit-notice", "asis", "no-liability"]


def test_licence_lines_stay_apart():
    assert licences.scan_text("- released under the MIT license\n- some words\nLicensed under the GNU Lesser General Public License, version 3\nMore")[0] == ["MIT", "LGPL-3.0-only"]
    assert licences.scan_text("This work is licensed\n# under the MIT License; it says.")[0] == ["MIT"]
    assert licences.scan_text("Some words; the data are released under CC0.")[:2] == (["CC0-1.0"], [1])
    assert licences.scan_text("In no event shall the authors go. They may be liable.")[0] == []


def test_licence_scan_rows(spark, odd, empty):
    assert licences.scan(odd).count() == 14 and licences.scan(empty).count() == 0


# 3 and 9


@settings(max_examples=150, deadline=None)
@given(st.text(max_size=60))
def test_encoder_equals_library(text):
    e = tokens.encoder(tokens.default_tokenizer_path())
    assert e.encode(text) == (e.whole(text) if text else b"")


def test_encoder_on_real_and_odd_texts(spark, small):
    e = tokens.encoder(tokens.default_tokenizer_path())
    texts = [r.text for r in spark.read.parquet(f"{small}/documents.parquet").limit(60).collect()]
    for t in [*texts, "a\x7fb \x7f", "It's <|endoftext|>x ’s", "Σας ΑΣ İx ﬁ Å \u0301e\u0301 \x1c\x1d", "x" * 5000]:
        assert e.encode(t) == e.whole(t)


def test_encoder_takes_each_piece_of_a_column_once(monkeypatch):
    import pyarrow as pa

    e = tokens.TextEncoder(tokens.default_tokenizer_path())
    seen, merged, pieces, merge = [], [], e._pieces, e.merge
    monkeypatch.setattr(e, "_pieces", lambda x: (seen.extend(x), pieces(x))[1])
    monkeypatch.setattr(e, "merge", lambda x: (merged.append(x), merge(x))[1])
    texts = ["left out", "Été été, ÉTÉ!! it's 42%", None, "", "été  it's\nété,\t<|endoftext|>. Ωmega's €5 o\u0301", "\x7f \r a\x7f", " "] * 3
    column = pa.array(texts).slice(1)
    assert list(e.encode_column(column)) == [e.whole(t) if t else b"" for t in texts[1:]]
    assert len(seen) == len(set(seen)) and len(merged) == len(set(merged))
    assert list(e.encode_column(column.slice(0, 0))) == []


def brute_ids(text, end):
    e = tokens.encoder(tokens.default_tokenizer_path())
    return (e.whole(text) if text else b"") + end.to_bytes(4, "little")


def test_token_file(spark, odd, empty, tmp_path):
    path = str(tmp_path / "t")
    token_file.write_token_file(odd, path)
    got = sorted(token_file.token_index(token_file.read_token_file(spark, path)).collect(), key=lambda r: r.start)
    order = sorted(odd.collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0))
    assert [r.doc_id for r in got] == [r.doc_id for r in order]
    start = 0
    for r in got:
        assert r.start == start
        ids = [brute_ids(x.text, 1) for x in order if x.doc_id == r.doc_id]
        assert (r.n_tokens, r.ids_crc32) in [(len(i) // 4, zlib.crc32(i)) for i in ids]
        start += r.n_tokens
    assert token_file.read_token_file(spark, path, [9]).count() == 1
    plan = token_file.read_token_file(spark, path, [9])._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [In(doc_id" in plan or "EqualTo(doc_id" in plan
    token_file.write_token_file(empty, str(tmp_path / "e"))
    assert token_file.token_index(token_file.read_token_file(spark, str(tmp_path / "e"))).count() == 0


def test_packing(spark, odd, empty):
    rows = packing.pack(odd, with_ids=True).collect()
    assert sorted(r.sequence_id for r in rows) == list(range(len(rows))) and all(r.offset == 0 and r.length & (r.length - 1) == 0 and r.length <= 4096 for r in rows)
    want = sorted(brute_ids(x.text, 2) for x in odd.collect())
    whole = {}
    for r in rows:
        assert zlib.crc32(r.ids) == r.ids_crc32
        whole.setdefault((r.doc_id, r.doc_tokens), []).append((r.start, bytes(r.ids)))
    assert sum(len(b) for v in whole.values() for _, b in v) == sum(map(len, want))
    one = b"".join(b for _, b in sorted(whole[(9, max(r.doc_tokens for r in rows))]))
    assert one in want
    lengths = [r.length for r in sorted(rows, key=lambda r: r.sequence_id)]
    assert lengths == sorted(lengths, reverse=True)
    assert packing.piece_lengths(4096 * 2 + 5) == [4096, 4096, 4, 1] and packing.piece_lengths(0) == []
    assert packing.pack(empty).count() == 0


# 4


@settings(max_examples=40, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(alphabet="aB \t\n\x0b\xa0é", max_size=40)), max_size=12))
def test_shingles_and_word_counts(texts):
    import pyarrow as pa

    column = pa.array(texts, pa.string())
    assert [len(s) for s in words.shingle_sets(column)] == [len(shingles(t)) for t in texts]
    assert words.word_counts(column).tolist() == [len(WORD.findall(t or "")) for t in texts]


def brute_components(rows):
    sets = [(i, shingles(t)) for i, t in rows if i is not None]
    parent = {i: i for i, _ in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for (a, s), (b, t) in itertools.combinations(sets, 2):
        if s and t and 100 * len(s & t) >= 75 * len(s | t):
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    return {(i, len(s), find(i)) for i, s in sets}


def test_ngram_components(spark, odd, empty):
    rng = random.Random(11)
    rows = []
    for g in range(12):
        base = [f"t{rng.randrange(3000)}" for _ in range(rng.randrange(1, 90))]
        passage = [f"p{i}" for i in range(30)]
        for _ in range(rng.randrange(1, 14)):
            w = list(base)
            for _ in range(rng.randrange(0, max(1, len(w) // 14) + 1)):
                w[rng.randrange(len(w))] = f"x{rng.randrange(9999)}"
            if rng.random() < 0.3:
                w = w + passage
            rows.append((len(rows) * 3 + 1, " ".join(w)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {tuple(r) for r in ngram_join.ngram_components(docs).collect()}
    assert got == brute_components(rows)
    small = [(r.doc_id, r.text) for r in odd.collect()]
    got = ngram_join.ngram_components(odd).collect()
    assert {tuple(r) for r in got if r.doc_id is not None} == brute_components(small) and len(got) == 14
    assert [tuple(r)[2] for r in got if r.doc_id is None] == [None]
    assert ngram_join.ngram_components(empty).count() == 0
    kept = ngram_join.first_of_each(odd)
    assert kept.columns == odd.columns and {3, 8} & {r.doc_id for r in kept.collect()} == set()


def test_all_links_are_given(spark, odd, empty):
    """Links within a group of near copies larger than a chunk, between groups, and of ids with several texts."""
    rng = random.Random(3)
    base = [f"g{i}" for i in range(120)]
    rows = []
    for _ in range(150):
        w = list(base)
        for _ in range(rng.randrange(0, 5)):
            w[rng.randrange(120)] = f"x{rng.randrange(10_000)}"
        rows.append((len(rows) + 1, " ".join(w), "en", "a"))
    rows += [(len(rows) + k, " ".join(base[k : 100 + k]), "en", "a") for k in range(1, 12)]
    rows += [(5, "five words are said here twice", "en", "a"), (7, "five words are said here twice", "en", "a"), (7, " ".join(base[:90]), "en", "a"), (None, " ".join(base), "en", "a"), (900, None, "en", "a")]
    for docs in (table(spark, rows), odd):
        seen = [(r.doc_id, frozenset(shingles(r.text))) for r in docs.collect()]
        texts = {s for i, s in seen if s and i is not None}
        want = {frozenset((s, t)) for s, t in itertools.combinations(texts, 2) if 100 * len(s & t) >= 75 * len(s | t)}
        pairs, members = ngram_join.ngram_links(docs)
        by_class = {}
        for r in members.collect():
            by_class.setdefault(r.class_id, set()).add(r.doc_id)
        ids = {s: frozenset(i for i, t in seen if t == s and i is not None) for s in texts}
        assert sorted(map(sorted, by_class.values())) == sorted(map(sorted, ids.values()))
        got = [tuple(sorted((sorted(by_class[r.a]), sorted(by_class[r.b])))) for r in pairs.collect()]
        assert sorted(got) == sorted(tuple(sorted(sorted(ids[s]) for s in x)) for x in want)
        counted = ngram_join.ngram_link_counts(docs)
        links = {s: sum(s in x for x in want) for s in texts}
        assert sorted((str(r.doc_id), r.n_shingles, r.n_links) for r in counted.collect()) == sorted((str(i), len(s), links[s] if s and i is not None else 0) for i, s in seen)
        plain = ngram_join.ngram_components(docs)
        assert sorted(map(str, counted.drop("n_links").collect())) == sorted(map(str, plain.collect()))
    assert ngram_join.ngram_link_counts(empty).count() == 0


def test_components(spark):
    edges = [(i, i + 1) for i in range(40)] + [(100, 200), (200, 150), (7, 7), (None, 3)]
    got = {r.node: r.component for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(1, 41)} | {200: 100, 150: 100}


# 5


def test_mix_with_clashing_columns(spark, odd):
    names = ["_at", "_of", "_first", "_before", "_part", "_row", "_tie", "row", "part", "of", "no", "n", "first", "before", "tie", "nth", "source_size", "copies", "size", "a.b"]
    plain = mixing.mix(odd).select("doc_id", "size", "source_size", "target", "copies").collect()
    clash = mixing.mix(odd.withColumns({c: F.lit(10) for c in names}))
    assert set(clash.columns) == {*odd.columns, *names, "target"}
    assert sorted(map(str, clash.select("doc_id", "size", "source_size", "target", "copies").collect())) == sorted(map(str, plain))
    assert all(r["_part"] == r["a.b"] == r["row"] == r["nth"] == 10 for r in mixing.take(clash).collect())
    counted = mixing.mix(odd.select("doc_id", "source", mixing.word_total().alias("words")), size="words")
    assert sorted(r.target for r in counted.collect()) == pytest.approx(sorted(r.target for r in plain))


def test_mix(spark, odd, empty):
    rows = mixing.mix(odd).collect()
    assert len(rows) == 14 and "size_" in rows[0].asDict()
    total = sum(r.size for r in rows)
    goal = {r.source: r.target for r in rows}
    assert sum(goal.values()) == pytest.approx(total)
    for r in rows:
        assert r.size == len(WORD.findall(r.text or "")) and r.target <= 3 * r.source_size + 1e-9 and 0 <= r.copies <= 3
    for s in goal:
        mine = [r for r in rows if r.source == s]
        assert abs(sum(r.copies * r.size for r in mine) - goal[s]) <= max(r.size for r in mine) + 1e-6
    again = mixing.mix(odd.repartition(7)).collect()
    key = lambda rs: sorted((str(r.doc_id), r.size, r.copies) for r in rs)
    assert key(rows) == key(again)
    assert mixing.take(mixing.mix(odd)).count() == sum(r.copies for r in rows) and mixing.mix(empty).count() == 0


# 6


@settings(max_examples=25, deadline=None)
@given(st.lists(st.text(alphabet="\\<>/turnlbg \n#:é😀", max_size=30), min_size=1, max_size=5))
def test_chat_round_trip(spark, texts):
    rows = [(1, i, "assistant" if i % 2 else "user", t) for i, t in enumerate(texts)]
    got = chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))
    r = got.join(chat.read_back(got), "conv_id").first()
    assert r.n_turns == len(texts)
    assert r.turns_sha256 == hashlib.sha256("".join(f"{x[2]}\n{x[3]}\n" for x in rows).encode()).hexdigest()
    learnt = [x[3] for x in rows if x[2] == "assistant"]
    assert r.loss_sha256 == hashlib.sha256("".join(learnt).encode()).hexdigest() and r.loss_chars == sum(map(len, learnt))
    shown = [r.formatted[s.start : s.end] for s in r.loss_spans]
    decode = lambda s: s.replace("\\g", ">").replace("\\l", "<").replace("\\b", "\\")
    assert [decode(s) for s in shown] == learnt


def test_chat_edges(spark):
    schema = "conv_id long, turn long, role string, text string, formatted string"
    df = spark.createDataFrame([(None, None, None, None, "x"), (1, 0, "user", None, "x"), (1, 0, "user", None, "x"), (2, 1, "assistant", "</turn>\n<turn user>\nhi", "x")], schema)
    got = {r.conv_id: r for r in chat.read_back(chat.format_conversations(df)).collect()}
    assert (got[None].n_turns, got[1].n_turns, got[2].n_turns, got[2].loss_chars) == (1, 2, 1, 22)
    assert chat.format_conversations(df.limit(0)).count() == 0


def test_chat_mask_is_read(spark):
    rows = [(1, 0, "user", "hello <turn x"), (1, 1, "assistant", "a </turn> b 😀" + "long " * 900), (1, 2, "user", "</turn>"), (1, 3, "assistant", "\\\\l end"), (1, 4, "assistant", "")]
    got = chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))
    learnt = "".join(x[3] for x in rows if x[2] == "assistant")
    right = chat.read_back(got).first()
    assert (right.loss_chars, right.loss_sha256) == (len(learnt), hashlib.sha256(learnt.encode()).hexdigest())
    shifted = got.withColumn("loss_spans", F.expr("transform(loss_spans, x -> struct(x.start + 1 as start, x.end + 1 as end))"))
    assert chat.read_back(shifted).first().loss_sha256 != right.loss_sha256
    none = chat.read_back(got.withColumn("loss_spans", F.lit(None).cast("array<struct<start:bigint,end:bigint>>"))).first()
    assert (none.loss_chars, none.loss_sha256) == (0, hashlib.sha256(b"").hexdigest())
    shown = got.first()
    assert shown.formatted.count("</turn>") == shown.formatted.count("<turn ") == 5


def test_chat_escapes_the_extra_conversation(spark, small):
    shown = {}
    plain, chat.read_back = chat.read_back, lambda x: shown.setdefault("rows", x)
    try:
        queries.QUERIES["op6_chat_format"](spark, small)
    finally:
        chat.read_back = plain
    assert shown["rows"].where("conv_id = -7").first().formatted.count("</turn>") == 2


# 7


def test_top_k(spark):
    rng = random.Random(3)
    rows = [(i, [rng.choice([0.0, rng.uniform(-1, 1)]) for _ in range(8)]) for i in range(1, 400)] + [(50, [1.0] * 8), (401, [0.5] * 8), (402, [0.5] * 8), (403, None), (404, [float("nan")] * 8), (405, [None] * 8), (None, [1.0] * 8), (450, [0.5, 0.25])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("score", F.lit("clash"))
    import math

    import numpy as np

    good = [(i, [math.floor(256 * float(np.float32(x))) for x in v]) for i, v in rows if i is not None and v is not None and all(x is not None and math.isfinite(x) for x in v)]
    got = sorted(tuple(r) for r in maxscore.top_k(df.repartition(3)).collect())
    want = []
    for q in sorted({i for i, _ in good if i % 50 == 0}):
        scores = [(-sum(x * y for x, y in zip(v, w)), j) for i, v in good if i == q for j, w in good if j != q]
        want += [(q, n + 1, j, -s) for n, (s, j) in enumerate(sorted(scores)[:5])]
    assert got == sorted(want)
    assert maxscore.top_k(df.limit(0)).count() == 0


def test_top_k_prunes():
    import numpy as np

    rng = np.random.default_rng(0)
    rows = rng.integers(-50, 50, (2000, 16))
    rows[:, 3:] //= 20
    shard = maxscore.Shard(np.arange(2000), rows, counting=True)
    q = rows[7]
    scores = rows @ q
    floor = int(np.sort(scores)[-5])
    score, at = shard.search(q, -1, 5, floor)
    assert sorted(at.tolist()) == np.flatnonzero(scores >= floor).tolist() and (scores[at] == score).all()
    assert 0 < shard.read < shard.held / 2
    for at_term in range(16):  # lists are sorted by row and hold each non-zero value once
        for sign, (rows_of, values, _, ends) in enumerate(shard.lists):
            own = slice(ends[at_term], ends[at_term + 1])
            inside = rows[:, at_term] > 0 if sign else rows[:, at_term] < 0
            assert rows_of[own].tolist() == np.flatnonzero(inside).tolist() and (values[own] == rows[inside, at_term]).all()


def test_top_k_on_given_vectors_reads_fewer_postings(small):
    import numpy as np
    import pyarrow.parquet as pq

    table = pq.read_table(f"{small.replace('sf0.001', 'sf0.1')}/embeddings.parquet").to_pylist()
    rows = np.floor(256 * np.array([r["embedding"] for r in table], float)).astype(np.int64)
    shard = maxscore.Shard(np.arange(len(rows)), rows, counting=True)
    for q in rows[::50]:
        scores = rows @ q
        floor = int(np.sort(scores)[-5])
        score, at = shard.search(q, -1, 5, floor)
        assert sorted(at.tolist()) == np.flatnonzero(scores >= floor).tolist() and (scores[at] == score).all()
    assert shard.read < shard.held / 2


def test_top_k_with_huge_values_and_small_blocks(spark):
    import numpy as np

    rng = np.random.default_rng(4)
    rows = rng.integers(-(1 << 29), 1 << 29, (300, 6))
    shard = maxscore.Shard(np.arange(300), rows)
    for q in rows[:20]:
        scores = rows @ q
        floor = int(np.sort(scores)[-5])
        score, at = shard.search(q, -1, 5, floor)
        assert sorted(at.tolist()) == np.flatnonzero(scores >= floor).tolist() and (scores[at] == score).all()
    df = spark.createDataFrame([(i, [float(x) / 2**29 for x in v]) for i, v in enumerate(rows.tolist())], "vec_id long, embedding array<double>")
    once, often = maxscore.top_k(df, every=7), maxscore.top_k(df, every=7, query_bytes=500)
    assert sorted(once.collect()) == sorted(often.collect())


# 8


def plain_mix(x):
    x = (x ^ (x >> 30)) * words.MIX_1 % 2**64
    x = (x ^ (x >> 27)) * words.MIX_2 % 2**64
    return x ^ (x >> 31)


def test_imatch_splits_hot_ids(spark):
    """Null ids and one id with many texts fill several parts; every row still meets the row after it."""
    rng = random.Random(9)
    rows = [(i, f"doc {i} " + " ".join(rng.choice("abcdefgh") * 3 for _ in range(6))) for i in range(1, 30)]
    rows += [(12, f"hot {i} text {i * i} of one id") for i in range(60)] + [(None, f"null {i} row {i * 7}") for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = imatch.edit_test(docs, rows_per_part=8).collect()
    ties = {r.text: r.tie for r in docs.select("text", F.xxhash64("text").alias("tie")).collect()}
    order = sorted(rows, key=lambda r: (r[0] is None, -(r[0] or 0), ties[r[1]], r[1]))
    want = []
    for a, b in zip(order, order[1:] + order[:1], strict=True):
        cut = len(a[1]) // 3
        want.append((str(a[0]), hashlib.sha256((a[1][: len(a[1]) - cut] + b[1][:cut]).encode()).hexdigest()))
    assert sorted((str(r.doc_id), r.edited_sha256) for r in got) == sorted(want)


def test_imatch(spark, odd, empty):
    got = imatch.edit_test(odd, rows_per_part=4).collect()
    rows = sorted(odd.collect(), key=lambda r: (r.doc_id is None, -(r.doc_id or 0)))
    assert len(got) == 14
    texts = [r.text or "" for r in rows]
    edited = {}
    for i, r in enumerate(rows):
        cut = len(texts[i]) // 3
        new = texts[i][: len(texts[i]) - cut] + texts[(i + 1) % len(rows)][:cut]
        edited.setdefault(r.doc_id, set()).add(hashlib.sha256(new.encode()).hexdigest())
    for r in got:
        assert r.edited_sha256 in edited[r.doc_id] and 0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1
    prints = {r.doc_id: r.fingerprint for r in got}
    assert prints[1] == prints[2] == prints[None] and prints[1] != prints[9]
    lex = imatch.lexicon(odd)
    df = {}
    for t in texts:
        for w in set(WORD.findall(lower(t))):
            df[w] = df.get(w, 0) + 1
    import pyarrow as pa

    hashed = {w: int(next(words.distinct_words(pa.array([w])))[0]) for w in df}
    assert set(map(int, lex)) == {hashed[w] for w, n in df.items() if 2 <= n <= max(2, 0.25 * len(texts))}
    by_text = {t: next(imatch.prints_of(pa.array([t]), lex)) for t in texts}
    for t, own in by_text.items():  # the first hash by its definition, in plain integers
        terms = {hashed[w] for w in set(WORD.findall(lower(t)))}
        base = terms & set(map(int, lex)) or terms
        assert own.split(" ")[0] == (f"{sum(map(plain_mix, (x ^ 0xA5A5A5A5A5A5A5A5 for x in base))) % 2**64:016x}" if base else "-")
    want = sorted((r.doc_id is None, r.doc_id or 0, by_text[t]) for r, t in zip(rows, texts, strict=True))
    assert sorted((r.doc_id is None, r.doc_id or 0, r.fingerprint) for r in got) == want
    for r in got:
        levels = [(r.fingerprint.split(" ")[1 + 16 * i : 17 + 16 * i], r.edited_fingerprint.split(" ")[1 + 16 * i : 17 + 16 * i]) for i in range(5)]
        shares = [(sum(a == b for a, b in zip(*x, strict=True) if (a, b) != ("-", "-")), sum((a, b) != ("-", "-") for a, b in zip(*x, strict=True))) for x in levels]
        enough = [x for x in reversed(shares) if x[1] >= 8]
        same, of = enough[0] if enough else max(reversed(shares), key=lambda x: x[1])
        assert r.near_edited == pytest.approx(1.0 if r.fingerprint == r.edited_fingerprint else same / of if of else 0.0)
    assert imatch.edit_test(empty).count() == 0
    assert imatch.likeness("a", "a") == 1.0


def test_imatch_tells_edits_from_others(spark, small):
    got = imatch.edit_test(spark.read.parquet(f"{small}/documents.parquet")).toPandas()
    got = got[got.n_chars > 300]
    assert got.near_edited.mean() > got.near_next.mean() + 0.2


# 10


def test_language_id(spark, odd, empty, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    got = langid.identify(docs).where("held_out").select("lang", "lang_pred").collect()
    assert sum(r.lang == r.lang_pred for r in got) >= 0.95 * len(got) > 0
    rows = {r.doc_id: r for r in langid.identify(odd).collect()}
    assert {rows[i].lang_pred for i in (4, 5, 6, 12)} == {"und"} and rows[1].lang_pred == rows[2].lang_pred
    assert all(0 <= r.score <= 1 for r in rows.values()) and langid.identify(empty).count() == 0
    assert langid.train(docs, training_rows=40).langs == langid.train(docs).langs


def test_language_id_by_brute_force(spark, small):
    """Bayes by definition, with counters over n-grams, gives the languages and scores that the arrays give."""
    import math
    from collections import Counter

    docs = [r for r in spark.read.parquet(f"{small}/documents.parquet").limit(120).collect()]
    texts = [(r.lang, (r.text or "")[:300]) for r in docs if r.lang]
    langs = sorted({x for x, _ in texts})

    def grams(text):
        return Counter(next(x[2] for x in langid.gram_columns([text])).tolist())

    counts = {x: Counter() for x in langs}
    for lang, text in texts[::2]:
        counts[lang].update(grams(text))
    import numpy as np

    table = np.zeros((len(langs), langid.BUCKETS))
    for i, x in enumerate(langs):
        for k, n in counts[x].items():
            table[i, k] = n
    model = langid.Model(langs, table)
    total = {x: sum(counts[x].values()) + langid.SMOOTHING * langid.BUCKETS for x in langs}
    names, scores = model.predict([t for _, t in texts])
    for (_, text), name, score in zip(texts, names, scores, strict=True):
        if not any(c.isalpha() for c in text):
            assert (name, score) == ("und", 0)
            continue
        log = {x: sum(n * math.log((counts[x][k] + langid.SMOOTHING) / total[x]) for k, n in grams(text).items()) / len(langid.GRAMS) for x in langs}
        top = max(log.values())
        odds = {x: math.exp(v - top) for x, v in log.items()}
        assert score == pytest.approx(odds[name] / sum(odds.values()), rel=1e-3) and odds[name] > 0.99


def test_language_id_with_clashing_columns(spark, odd):
    names = ["_found", "found", "row", "lang_pred", "score", "held_out", "a.b"]
    got = langid.identify(odd.withColumns({c: F.lit("x") for c in names}))
    assert set(got.columns) == {*odd.columns, *names}
    assert all(r["_found"] == r["found"] == r["row"] == r["a.b"] == "x" and r.lang_pred != "x" and r.held_out != "x" for r in got.collect())
    assert sorted(str(tuple(r)) for r in got.select("doc_id", "lang_pred").collect()) == sorted(str(tuple(r)) for r in langid.identify(odd).select("doc_id", "lang_pred").collect())


def test_workers_keep_one_operator():
    from metricsearch.llm import workers

    list(tokens.encoded(["some words"], tokens.default_tokenizer_path()))
    assert tokens.encoder.cache_info().currsize >= 1
    workers.begin("tokens")
    assert tokens.encoder.cache_info().currsize >= 1
    workers.begin("words")
    assert tokens.encoder.cache_info().currsize == 0


def test_slices_are_bounded():
    import pyarrow as pa

    batch = pa.RecordBatch.from_arrays([pa.array(["a" * 10, None, "b" * 100, "", "c" * 5])], ["text"])
    got = [x["text"].to_pylist() for x in words.slices(iter([batch]), rows=3, size=20)]
    assert sum(got, []) == batch["text"].to_pylist() and [len(x) for x in got] == [2, 1, 2]


# The pipeline


def test_pipeline_stages_on_odd_tables(spark, odd, empty, small):
    """Nulls, blanks, repeats, a very long text and clashing columns go through every stage; an empty table too."""
    import corpus_pipeline

    clash = odd.withColumns({c: F.lit("x") for c in ("_found", "row", "size", "part", "component_id", "score", "ids", "node")})
    rows = odd.collect()
    kept = {name: stage(spark, clash, small) for name, stage in corpus_pipeline.STAGES[:1]}
    assert {r.doc_id for r in kept["language_id"].collect()} <= {r.doc_id for r in rows if any(c.isalpha() for c in r.text or "")}
    want = {i for i, _, c in brute_components([(r.doc_id, r.text) for r in rows]) if i == c} | {None}
    assert {r.doc_id for r in corpus_pipeline.one_of_each(spark, clash, small).collect()} == want
    assert corpus_pipeline.target_mix(spark, clash, small).columns == corpus_pipeline.COLUMNS
    assert sum(r.length for r in corpus_pipeline.packed(spark, clash, small).collect()) == sum(len(brute_ids(r.text, 2)) // 4 for r in rows)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, small).count() == 0


def test_two_runs_do_not_touch_each_other(spark, small):
    import corpus_pipeline

    first, second = corpus_pipeline.run(spark, small), corpus_pipeline.run(spark, small)
    columns = ["doc_id", "start", "length", "ids_crc32"]
    assert sorted(first.select(*columns).collect()) == sorted(second.select(*columns).collect())


def test_pipeline(spark, small):
    import corpus_pipeline

    docs = spark.read.parquet(f"{small}/documents.parquet")
    first = corpus_pipeline.known_language(spark, docs, small)
    ids = {r.doc_id: r.text for r in first.select("doc_id", "text").collect()}
    assert len(ids) >= 0.95 * docs.count()
    comp = {i: c for i, _, c in brute_components(list(ids.items()))}
    out = corpus_pipeline.run(spark, small).collect()
    kept = {i for i, c in comp.items() if i == c}
    assert {r.doc_id for r in out} <= kept
    taken = mixing.mix(docs.where(F.col("doc_id").isin(list(kept)))).where("copies > 0").collect()
    assert {r.doc_id for r in out} == {r.doc_id for r in taken}
    e = tokens.encoder(tokens.default_tokenizer_path())
    assert sum(r.length for r in out) == sum(r.copies * (len(e.whole(r.text)) // 4 + 1) for r in taken)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "ngram_join", "source_mix", "packing"]


@pytest.mark.parametrize("name", ["op4_ngram_join", "op5_source_mix", "op6_chat_format", "op7_maxscore"])
def test_twins(spark, small, name):
    import duckdb

    from metricsearch.llm.sql import ORACLES

    con = duckdb.connect()
    for t in ("documents", "embeddings", "conversations"):
        con.execute(f"create view {t} as select * from '{small}/{t}.parquet'")
    got, want = queries.QUERIES[name](spark, small).toPandas(), con.execute(ORACLES[name]).df()
    columns = sorted(got.columns)
    key = lambda df: sorted(tuple(str(round(x, 6)) if isinstance(x, float) else str(x) for x in r) for r in df[columns].itertuples(index=False))
    assert columns == sorted(want.columns) and key(got) == key(want)


def test_link_counts_twin(spark, small):
    test_twins(spark, small, "op4_ngram_links")


def test_scratch_is_released(spark):
    import os

    scratch.write_table(spark.range(3), "t", "mine")
    path = scratch.new_path(spark, "t", "mine")
    spark.range(2).write.parquet(path)
    assert os.path.exists(path.removeprefix("file://"))
    scratch.release(spark, "mine")
    assert not os.path.exists(path.removeprefix("file://"))


def test_pipeline_language_stage_sends_small_batches(spark, small, monkeypatch):
    """The rows are written while the bound on batches holds: a lazy result would be sent without it."""
    import corpus_pipeline

    seen, write = [], scratch.write_table
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    monkeypatch.setattr(corpus_pipeline.scratch, "write_table", lambda df, *a, **b: (seen.append(int(spark.conf.get(key))), write(df, *a, **b))[1])
    before = spark.conf.get(key)
    docs = spark.read.parquet(f"{small}/documents.parquet")
    kept = corpus_pipeline.known_language(spark, docs, small)
    assert seen == [1 << 20] and spark.conf.get(key) == before
    assert "ArrowEvalPython" not in kept._jdf.queryExecution().executedPlan().toString()
    found = langid.identify(docs.select(*corpus_pipeline.COLUMNS)).where(f"lang_pred <> '{langid.UNKNOWN}' and score >= {corpus_pipeline.LEAST_SCORE}")
    assert sorted(r.doc_id for r in kept.collect()) == sorted(r.doc_id for r in found.collect())


def test_encoder_with_few_words():
    """A smaller table of words gives the same ids."""
    path = tokens.default_tokenizer_path()
    few, texts = tokens.TextEncoder(path, 50), [" ".join(f"word{i * j} x{i}" for i in range(90)) for j in range(5)]
    for text in texts:
        assert few.encode(text) == few.whole(text)
    assert len(few.words.young) <= 50 and len(few.words.old) <= 50
