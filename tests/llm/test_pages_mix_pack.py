import re
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from pagesketch.llm import license_scan, mixing, packing, url_filter
from pagesketch.llm.common import Texts, join_with_hot_keys, table
from pagesketch.llm.queries import tokenizer_path

PAGES = "page_id bigint, url string, html string, host string, rule string, verdict string"


def link(url):
    return f'<head><LINK href="{url}" rel="canonical"></head>'


def refresh(url):
    return f'<meta http-equiv="refresh" content="0; url={url}">'


def test_url_rules(spark, none):
    cases = {
        "https://a.net/x": ("a.net", "/x", "net/", "block"),
        "http://www.Example.NET/en/1?q": ("www.example.net", "/en/1", "example.net/en/", "allow"),
        "http://example.com/de/9#t": ("example.com", "/de/9", "example.com/de/", "block"),
        "http://notexample.com/de/9": ("notexample.com", "/de/9", None, "allow"),
        "http://x.org/fr/": ("x.org", "/fr/", "org/fr/", "allow"),
        "http://a.net": ("a.net", "", None, "allow"),
        "http://a.net?x=/": ("a.net", "", None, "allow"),
        "no scheme/net/": ("", "", None, "allow"),
        None: ("", "", None, "allow"),
        "a://b://c.net/": ("b:", "//c.net/", None, "allow"),
    }
    pages = spark.createDataFrame([(i, u, None, None, None, None) for i, u in enumerate(cases)], PAGES)
    got = {r["page_id"]: tuple(r)[1:] for r in url_filter.judge_urls(pages).collect()}
    assert got == dict(enumerate(cases.values()))
    assert url_filter.judge_urls(spark.createDataFrame([], PAGES)).count() == 0


def test_aliases(spark):
    rows = [
        (1, "http://a.com/1", link("http://b.com/1")),
        (2, "https://b.com/1", refresh("http://bad.net/x")),
        (3, "http://c.com/1", link("http://example.net/en/5")),
        (4, "http://d.com/1", link("http://c.com/1") + refresh("http://bad.net/y")),
        (5, "http://e.com/1", "<p>canonical refresh</p>"),
        (6, "http://f.com/1", link("http://f.com/1")),
        (6, "http://f.com/1", link("http://f.com/1")),
        (7, "http://bad.net/z", link("http://example.net/en/5")),
    ]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    redirects = spark.createDataFrame([("http://e.com/1", "http://g.com/"), ("https://g.com/", "http://h.net/"), (None, "http://a.com/1")], "src_url string, dst_url string")
    got = sorted((r["page_id"], r["verdict"]) for r in url_filter.judge_urls(pages, redirects=redirects).collect())
    assert got == [(1, "block"), (2, "block"), (3, "allow"), (4, "allow"), (5, "block"), (6, "allow"), (6, "allow"), (7, "block")]


def test_relative_and_repeated_aliases(spark):
    rows = [
        (1, "http://a.com/x/y?q", link("/bad")),
        (2, "http://b.com/x/y?q#f", link("z/../bad")),
        (3, "http://c.com/x/y?q", link("?id=1")),
        (4, "http://d.com/x", refresh("next.html")),
        (5, "http://e.com/x", link("//bad.net/x")),
        (6, "http://f.com/x", link("") + link("#top") + refresh("") + link("http://ok.info/") + link("//bad.net/x") + refresh("http://ok.info/2")),
        (7, "http://g.com", link("bad")),
        (8, "http://h.com/", link("mailto:a@b") + link("javascript:go('http://bad.net/x')") + link("/go?u=http://bad.net/x")),
        (9, "http://i.com/x", '<base href="//j.com/deep/">' + link("../bad")),
        (10, None, link("/bad")),
        (11, "http://k.com/a/b/", link("../../../bad/.")),
        (12, "http://l.com/x", refresh("http://ok.info/3") + refresh("https://bad.net/x")),
        (13, "http://m.com/x", link("http&#58;//bad.net/x")),
        (14, "http://n.com/x", link("/y?a=1&amp;b=2") + refresh("/y?a=1&amp;c=3")),
    ]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string")
    bad = ["a.com/bad", "b.com/x/bad", "c.com/x/y?id=1", "d.com/next.html", "g.com/bad", "j.com/bad", "k.com/bad/", "n.com/y?a=1&c=3"]
    redirects = spark.createDataFrame([(f"http://{u}", "http://bad.net/x") for u in bad], "src_url string, dst_url string")
    got = {r["page_id"]: r["verdict"] for r in url_filter.judge_urls(pages, redirects=redirects).collect()}
    assert got == {i: "allow" if i in (8, 10) else "block" for i in range(1, 15)}


def test_license_inheritance(spark):
    apache, mit = license_scan.TEMPLATES["Apache-2.0"][0], license_scan.TEMPLATES["MIT"][0]
    rows = [
        (1, "repo/LICENSE", "Some words\n" + apache),
        (2, "repo/src/a.py", "print(1)"),
        (3, "repo/src/deep/b.py", "// " + mit + "\ncode"),
        (4, "repo/src/lib/LICENSE.txt", mit),
        (5, "repo/src/lib/x/y/z.c", "int x;"),
        (6, "repository/a.c", "int y;"),
        (7, "README", "This says copyright and little else that fits a notice of any kind at all"),
        (8, None, None),
        (9, "repo/empty", ""),
    ]
    files = spark.createDataFrame(rows, "doc_id bigint, path string, text string").withColumn("license", F.lit("clash"))
    got = {r["doc_id"]: (r["license"], r["found_by"], r["inherited_from"]) for r in license_scan.scan(files, F.col("path")).collect()}
    assert got[1] == ("Apache-2.0", "header", None) and got[2] == ("Apache-2.0", "inherited", "repo")
    assert got[3] == ("MIT", "header", None) and got[5] == ("MIT", "inherited", "repo/src/lib")
    assert got[6] == got[7] == got[8] == (None, "none", None) and got[9][1] == "inherited"


def test_spdx_identifiers(spark):
    lines = {
        "SPDX-License-Identifier: MIT": "MIT",
        "// SPDX-License-Identifier: GPL-3.0": "GPL-3.0",
        "/* spdx-license-identifier:\tLGPL-3.0-or-later */": "LGPL-3.0",
        "# SPDX-License-Identifier: (Foo-1.0 OR GPL-3.0+)": "GPL-3.0",
        "# SPDX-License-Identifier: MPL-2.0 AND Apache-2.0.": "Apache-2.0",
        "SPDX-License-Identifier: GPL-1.0-only": None,
        "SPDX-License-Identifier: GPL-2.0-only": "GPL-2.0",
        "SPDX-License-Identifier: MIT-0": None,
        "SPDX-License-Identifier: Foo-1.0 like MIT": None,
    }
    files = spark.createDataFrame([(i, f"x{i}/a.c", f"int a;\n{t}\nint b;") for i, t in enumerate(lines)], "doc_id bigint, path string, text string")
    got = {r["doc_id"]: (r["license"], r["cosine"]) for r in license_scan.scan(files, F.col("path")).collect()}
    assert got == {i: (k, k and 1.0) for i, k in enumerate(lines.values())}


def test_notices_in_lines_sentences_and_paragraphs(spark):
    gpl = "/*\n * This program is free software; you can redistribute it and/or modify\n * it under the terms of the GNU General Public License as published by\n * the Free Software Foundation; either version {} of the License, or\n * (at your option) any later version.\n */\nint a;"
    files = {
        "Redistribution and use in source and binary forms, with or without\nmodification, are permitted provided that the following conditions are met:\n\n1. first": "BSD-3-Clause",
        gpl.format(2): "GPL-2.0",
        gpl.format(3): "GPL-3.0",
        "                    GNU GENERAL PUBLIC LICENSE\n                       Version 3, 29 June 2007\n\n Everyone may copy.": "GPL-3.0",
        "GNU Affero GPL v3": "AGPL-3.0",
        "Use it under GPL version 2": "GPL-2.0",
        "Mozilla Public License Version 2.0": "MPL-2.0",
        "Great tool for you. Released under the MIT License. It was written long ago by many people in many places who cared.": "MIT",
        "x\n\nPermission is hereby granted, free of charge, to any person obtaining a copy\nof this software and associated documentation files, to deal\nin the Software without restriction, including without limitation the rights\nto use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies": "MIT",
        "# Licensed under the Apache License, Version 2.0 (the License);\n# you may not use this file except in compliance with the License.\nimport a": "Apache-2.0",
        "This copyright is held by nobody whom we know": None,
    }
    rows = [(i, f"x{i}/a.c", t) for i, t in enumerate(files)]
    got = {r["doc_id"]: r["license"] for r in license_scan.scan(spark.createDataFrame(rows, "doc_id bigint, path string, text string"), F.col("path")).collect()}
    assert got == dict(enumerate(files.values()))


def test_whole_licence_files(spark):
    """A licence file is compared as a whole, with full texts that the caller brings; ties go to the first name."""
    full = "You may copy this work freely. " * 3 + "Keep these words. No promise is made."
    rows = [(1, "r/COPYING", full.replace(" ", "\n")), (2, "r/a.c", "int a;"), (3, "s/a.c", full)]
    files = spark.createDataFrame(rows, "doc_id bigint, path string, text string")
    got = {r["doc_id"]: (r["license"], r["cosine"], r["found_by"]) for r in license_scan.scan(files, F.col("path"), templates={"Own-2": full, "Own-1": full}).collect()}
    assert got == {1: ("Own-1", 1.0, "header"), 2: ("Own-1", None, "inherited"), 3: (None, None, "none")}


def test_licenses_of_odd_rows(odd, odd_rows, none):
    path = F.concat_ws("/", "source", F.col("doc_id").cast("string"))
    got = license_scan.scan(odd, path)
    assert got.count() == len(odd_rows) and got.where("doc_id = 13 and license = 'Apache-2.0' and cosine = 1").count() == 1
    assert license_scan.scan(none, path).count() == 0


def fill(total, children):
    """Budgets by pouring: children (weight, capacity), in fractions."""
    out, open_ = [0.0] * len(children), set(range(len(children)))
    while open_ and total - sum(out) > 1e-9:
        rest, w = total - sum(out), sum(children[i][0] for i in open_)
        for i in sorted(open_):
            out[i] += rest * children[i][0] / w
        full = {i for i in open_ if out[i] >= children[i][1] - 1e-9}
        for i in full:
            out[i] = children[i][1]
        open_ -= full
        if not full:
            break
    return out


def test_mixing(spark, sf):
    docs = table(spark, sf, "documents")
    got = mixing.mix(docs)
    tokens = {r["doc_id"]: (r["lang"], r["source"], len(re.findall(r"[^\x20\x09-\x0D]+", r["text"] or ""))) for r in docs.collect()}
    tree = defaultdict(int)
    for lang, source, n in tokens.values():
        digit = source[-1]
        tree[("web" if digit in "01234" else "reference" if digit in "567" else "forum"), lang, source] += n
    cap = {k: 3 * n for k, n in tree.items()}
    total = min(sum(cap.values()), sum(tree.values()) * 900 // 1000)
    domains = sorted({k[0] for k in tree})
    top = dict(zip(domains, fill(total, [(mixing.WEIGHTS["domain"][d], sum(c for k, c in cap.items() if k[0] == d)) for d in domains]), strict=True))
    taken = defaultdict(int)
    for r in got.collect():
        taken[r["domain"], r["lang"], r["source"]] += r["taken_tokens"]
        assert 0 < r["taken_tokens"] <= r["n_tokens"] == tokens[r["doc_id"]][2]
    assert sum(taken.values()) == total
    for d in domains:
        assert abs(sum(v for k, v in taken.items() if k[0] == d) - top[d]) < len(tree)
        langs = sorted({k[1] for k in tree if k[0] == d})
        mid = dict(zip(langs, fill(top[d], [(mixing.WEIGHTS["lang"][x], sum(c for k, c in cap.items() if k[:2] == (d, x))) for x in langs]), strict=True))
        for x in langs:
            assert abs(sum(v for k, v in taken.items() if k[:2] == (d, x)) - mid[x]) < len(tree)
    partial = defaultdict(int)
    for r in got.collect():
        partial[r["domain"], r["lang"], r["source"]] += r["taken_tokens"] < r["n_tokens"]
    assert max(partial.values()) <= 1


def test_mixing_of_odd_rows(odd, none):
    got = mixing.mix(odd, permille=3000)
    assert got.agg(F.max("epoch")).first()[0] == 3 and got.where("lang = '?'").count() > 0
    assert got.where("doc_id in (0, 1, 2)").count() == 0
    assert got.where("doc_id = 5").count() == 9
    assert mixing.mix(none).count() == 0


WORD = re.compile(r"[^\x20\x09-\x0D]+")


def test_mixed_texts_are_cut_where_the_budget_ends(spark, sf):
    docs = table(spark, sf, "documents")
    own = {r["doc_id"]: r for r in docs.collect()}
    mixed = mixing.Mix(docs, max_epochs=2, weights={"lang": {"en": 90, "de": 10}}, other_weight=5, domain=lambda source: F.substring(source, 1, 4))
    want = sorted((r["doc_id"], r["taken_tokens"]) for r in mixed.selection().collect())
    rows = mixed.texts()
    assert rows.columns == docs.columns
    got = rows.collect()
    assert sorted((r["doc_id"], len(WORD.findall(r["text"]))) for r in got) == want
    assert len({d for d, _ in want}) < len(want) and any(len(WORD.findall(own[d]["text"])) > n for d, n in want)
    for r in got:
        whole = own[r["doc_id"]]
        assert whole["text"].startswith(r["text"]) and r["n_chars"] == (whole["n_chars"] if r["text"] == whole["text"] else len(r["text"]))


def test_mixing_rows_without_id_and_with_one_id(spark):
    rows = [(None, f"w{i} x y z", "en", "s1") for i in range(40)] + [(7, "a b c d", "en", "s1"), (7, "e f g h", "en", "s1")]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string")
    mixed = mixing.Mix(docs, permille=500, max_epochs=1)
    taken = mixed.selection().agg(F.sum("taken_tokens")).first()[0]
    assert 83 <= taken <= 84
    texts = [r["text"] for r in mixed.texts().collect()]
    assert sum(len(t.split()) for t in texts) == taken and len(set(texts)) == len(texts)


def ids_of(path, texts):
    from tokenizers import Tokenizer

    return [x.ids for x in Tokenizer.from_file(path).encode_batch([t or "" for t in texts], add_special_tokens=False)]


ODD = ["It's we'll I'M foo's.", "a.b,c!! d.'s x.,;y", "İstanbul ΣΑΣ ς ﬁ", "éa.́ b̸.̸", "12.5 a1.b2 _x.y-z", "<|endoftext|> a.<|startoftext|>b <|x", "can't.'re'lls"]


def test_word_tokens():
    path = tokenizer_path()
    model = packing.WordTokenizer(path, cached_words=3)
    for texts in (ODD, ODD[::-1]):
        assert [np.frombuffer(x, "<u2").tolist() for x in model.encode(Texts(pa.array(texts)))] == ids_of(path, texts)
        assert len(model.cache) <= 3 + 60


@pytest.mark.parametrize("window", [7, 2048])
def test_packing_round_trip(odd, odd_rows, none, window):
    path = tokenizer_path()
    got = packing.pack(odd, path, window=window).collect()
    want = sorted(zlib.crc32(np.array([*i, 1], "<u4").tobytes()) for i in ids_of(path, [r[1] for r in odd_rows]))
    ids = {r[0]: [*i, 1] for r, i in zip(odd_rows, ids_of(path, [r[1] for r in odd_rows]), strict=True)}
    places = sorted((r["sequence_id"], r["offset"], r["length"]) for r in got)
    at = 0
    for sequence, offset, length in places:
        assert (sequence, offset) == divmod(at, window) and offset + length <= window
        at += length
    assert at == sum(len([*i, 1]) for i in ids_of(path, [r[1] for r in odd_rows]))
    for r in got:
        own = ids[r["doc_id"]]
        assert r["doc_tokens"] == len(own)
        assert r["ids_crc32"] == zlib.crc32(np.array(own[r["start"] : r["start"] + r["length"]], "<u4").tobytes())
    if window == 2048:
        whole = [r["ids_crc32"] for r in got if r["length"] == r["doc_tokens"]]
        assert set(whole) <= set(want)
    assert packing.pack(none, path).count() == 0


def test_hot_keys(spark):
    left = spark.createDataFrame([(1, i) for i in range(50)] + [(2, 99), (3, 98), (None, 97)], "k bigint, x bigint")
    right = spark.createDataFrame([(1, 50, "a"), (2, 1, "b")], "k bigint, n bigint, v string")
    got = {(r["k"], r["v"]) for r in join_with_hot_keys(left, right, ["k"], "n", 53, shares=2).collect()}
    assert got == {(1, "a"), (2, "b"), (3, None), (None, None)}


def test_pipeline(spark, sf):
    docs = table(spark, sf, "documents")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, docs, sf).cache()
        assert kept.columns == docs.columns and kept.count() <= docs.count(), name
        assert kept.select("doc_id").distinct().count() == kept.count()
        docs = kept
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "exact_dedup", "near_dedup", "mixing", "packing"]
    pieces = corpus_pipeline.run(spark, sf)
    assert sorted({r["doc_id"] for r in pieces.collect()}) == sorted(r["doc_id"] for r in docs.collect())


def test_pipeline_of_odd_rows(spark, odd, none, sf):
    for docs in (odd, none):
        for _, stage in corpus_pipeline.STAGES:
            stage(spark, docs, sf).collect()
