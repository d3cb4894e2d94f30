"""Operators against brute force, with nulls, empty and long texts, ties, repeated rows, empty tables and extra columns."""

import math
import random
import re
import zlib
from array import array
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from mediarel.llm import bpe, common, html_text, language, licenses, mixing, near_dup, neighbours, quality, token_counts, token_files

WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long, extra string"


def docs_of(spark, rows):
    return spark.createDataFrame([(i, t, g, s, len(t or ""), "e") for i, t, g, s in rows], DOCS)


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls in any column, blank, one-word, very long and repeated texts."""
    rng = random.Random(4)
    long = " ".join(rng.choice("alpha beta gamma delta epsilon".split()) for _ in range(30_000))
    rows = [(1, None, "en", "a"), (2, "", None, None), (3, " \t\n", "en", "a"), (4, "one", "fr", "b"), (5, long, "en", "a"), (6, "x y z\nx y z\n\nx", None, "b"), (7, "x y z\nx y z\n\nx", "en", None), (8, "Ünï cödé 日本 word\x1cword \x85 end", "de", "c")]
    return docs_of(spark, rows)


def empty(spark):
    return docs_of(spark, [(1, "a", "en", "a")]).where("false")


# 1 quality -----------------------------------------------------------------------------------------------------------


def brute_statistics(text):
    words = WORD.findall(text or "")
    grams = Counter(tuple(words[i : i + 5]) for i in range(len(words) - 4))
    covered = {p for i in range(len(words) - 4) if grams[tuple(words[i : i + 5])] > 1 for p in range(i, i + 5)}
    lines = [x for x in (text or "").split("\n") if WORD.search(x)]
    return len(words), sum(map(len, words)), sum((text or "").count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered)


def test_statistics_against_brute_force(spark, odd):
    rng = random.Random(1)
    rows = [(100 + i, "".join(rng.choice(["a", "b", "c ", " ", "\n", "#", "|", "é "]) for _ in range(rng.randrange(200))), "en", "s") for i in range(60)]
    for df in (odd, docs_of(spark, rows)):
        for r in quality.with_statistics(df).collect():
            assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == brute_statistics(r.text)
            assert r.base_failed == (r.n_words < 10 or 100 * r.n_repeat_words > 20 * r.n_words)


def test_rules_separate_and_judge(spark, odd):
    rng = random.Random(2)
    rows = [{"bad": b, **dict.fromkeys(quality.STATS, 0.0), "symbol_share": rng.uniform(0.2, 0.4) if b else rng.uniform(0, 0.1), "n_words": rng.randrange(10, 500)} for b in [True] * 60 + [False] * 300]
    rng.shuffle(rows)
    rules = quality.learn_rules(rows)
    assert rules and all(any(all(t.holds(r) for t in rule) for rule in rules) == r["bad"] for r in rows)
    assert quality.learn_rules([r for r in rows if r["bad"]]) == [] == quality.learn_rules([])
    judged = quality.judge(odd, rules)
    assert judged.count() == odd.count() and "extra" in judged.columns and judged.where("kept IS NULL").count() == 0
    assert quality.judge(empty(spark), []).count() == 0


# 2 near duplicates ---------------------------------------------------------------------------------------------------


def brute_components(rows, width, per_cent):
    sets = {}
    for i, t in rows:
        w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[i] = {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} if len(w) >= width else {tuple(w)} if w else set()
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            same = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * same >= per_cent * (len(sets[a]) + len(sets[b]) - same):
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


@pytest.mark.parametrize("seed", [1, 2])
def test_near_duplicates_against_all_pairs(spark, monkeypatch, seed):
    monkeypatch.setattr(near_dup, "HOT_LEAST", 6)  # makes families of frequent values on small data
    monkeypatch.setattr(near_dup, "COUNT_BLOCK", 400 * seed)  # and misses some of them at first
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(400)]
    base = [rng.choice(vocabulary) for _ in range(120)]
    rows = []
    for i in range(60):
        copy = list(base)
        for _ in range(rng.randrange(7)):
            copy[rng.randrange(120)] = f"n{rng.randrange(10_000)}"
        rows.append((i, " ".join(copy)))
    passage = " ".join(rng.choice(vocabulary) for _ in range(30))
    rows += [(100 + i, " ".join([*(rng.choice(vocabulary) for _ in range(60)), passage])) for i in range(30)]
    rows += [(200, None), (201, ""), (202, "a b"), (203, "A  b"), (204, "a b c"), (300, rows[3][1]), (301, rows[3][1].upper().lower())]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dup.link(docs_of(spark, [(i, t, "en", "s") for i, t in rows]), 3, 85).collect()}
    assert got == brute_components(rows, 3, 85)


def test_near_duplicates_of_odd_tables(spark, odd):
    out = {r.doc_id: r for r in near_dup.link(odd).collect()}
    assert out[1].component_id == 1 and out[1].kept and out[1].n_shingles == 0 and out[7].component_id == 6 and not out[7].kept
    assert near_dup.link(empty(spark)).count() == 0


def test_doc_ids_with_two_texts(spark):
    import corpus_pipeline

    rng = random.Random(11)
    text = lambda: [rng.choice("abcdefghijklmnopqrstuvwxyz") * rng.randrange(1, 9) for _ in range(150)]
    copied, other, lone = text(), text(), text()
    near = [*other[:-1], "changed"]
    rows = [(1, copied), (5, copied), (5, other), (7, near), (8, lone), (8, lone), (9, copied), (9, near)]
    docs = docs_of(spark, [*((i, " ".join(w), "en", "s") for i, w in rows), (None, "x y", "en", "s"), (None, "x y", "en", "s")])
    out = near_dup.link(docs).collect()
    assert len(out) == len(rows) + 2
    assert {r.doc_id: r.component_id for r in out if r.doc_id} == {1: 1, 5: 1, 7: 1, 8: 8, 9: 1}
    kept = corpus_pipeline.without_near_duplicates(spark, docs, "")
    assert kept.columns == docs.columns
    assert Counter((r.doc_id, r.text) for r in kept.collect()) == Counter([(1, " ".join(copied)), (5, " ".join(other)), (8, " ".join(lone)), (None, "x y"), (None, "x y")])


@pytest.mark.parametrize("per_cent", [50, 80, 85, 95])
def test_sketches_drop_links_with_less_than_the_stated_chance(per_cent):
    t, least = per_cent / 100, near_dup.least_shared(per_cent)
    chance = lambda m: sum(math.comb(near_dup.SKETCH, k) * t**k * (1 - t) ** (near_dup.SKETCH - k) for k in range(m))
    assert chance(least) <= near_dup.DROP_CHANCE < chance(least + 1)


# 3 language ----------------------------------------------------------------------------------------------------------


def test_bitmask_filter_counts_every_language():
    filt = language.BitmaskFilter.build(["a", "b"], [(1, 0), (2, 0), (2, 1), (3, 1)], slots=1 << 10)
    assert filt.hits(np.array([1, 2, 3, 4], dtype=np.uint64)).tolist() == [2, 2]
    many = language.BitmaskFilter.build([f"l{i:02d}" for i in range(70)], [(5, 69), (5, 3)], slots=1 << 10)
    hits = many.hits(np.array([5], dtype=np.uint64))
    assert hits[69] == 1 and hits[3] == 1 and hits.sum() == 2
    assert filt.compact().hits(np.array([1, 2, 3, 4], dtype=np.uint64)).tolist() == [2, 2]


def test_language_of_held_out_documents(spark, sf_dir, odd):
    docs = common.table(spark, "/root/testdata/sf0.01", "documents")
    model = language.fit(docs.where(~language.held_out(F.col("doc_id"))))
    told = language.predict(docs, model).where(language.held_out(F.col("doc_id")))
    assert told.where("lang = lang_pred").count() >= 0.97 * told.count()
    out = {r.doc_id: r for r in language.predict(odd, model).collect()}
    assert out[1].lang_pred == out[2].lang_pred == out[3].lang_pred == "und" and out[1].score == 0 and 0 <= out[8].score <= 1
    nothing = language.fit(empty(spark))
    assert {r.lang_pred for r in language.predict(odd, nothing).collect()} == {"und"}


# 4, 5 tokens ---------------------------------------------------------------------------------------------------------


@pytest.fixture(scope="module")
def coder():
    with open(bpe.vocabulary_path(), encoding="utf-8") as f:
        return bpe.ForcedBoundaryBpe(f.read())


def test_encoding_equals_the_library(coder):
    rng = random.Random(5)
    alphabet = [*"abcdefghijklmnopqrstuvwxyzABC 0123456789 \t\n\r\x0b\x0c\x1c\x1f\x85\xa0'.,!?_-#$²½éÉßİıΣσςñ日本語ا한́̈‘’“”…€™ªº×÷µ· 😀", "'s", "'ll", "<|endoftext|>", "<|startoftext|>", "the", "ing"]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randrange(40))) for _ in range(3000)] + ["a" * 5000 + "thé" * 900, "", "  "]
    library = coder.library()
    for t in texts:
        e = library.encode(t, add_special_tokens=False)
        want = array("I", e.ids).tobytes()
        assert coder.encode(t) == want and coder.decode(want) == library.decode(e.ids, skip_special_tokens=False), t
        assert coder.library_ids(t) == want


def test_cuts_are_forced(coder):
    for word in ("thonatst", "x1y2", "qzqzqz"):
        assert "".join(coder.cut(word)) == word
    assert all(a[-1] + b[0] not in coder.inner for a, b in zip(coder.cut("qzxjqk"), coder.cut("qzxjqk")[1:]))


def test_planes_round_trip():
    ids = np.random.default_rng(1).integers(0, 1 << 32, 1001, dtype=np.uint64).astype("<u4")
    for bits in (False, True):
        assert (token_files.from_planes(token_files.to_planes(ids, bits), len(ids)) == ids).all()


@pytest.mark.parametrize("bits", [False, True])
def test_files_round_trip(spark, odd, coder, tmp_path, bits):
    path = str(tmp_path / "files")
    token_files.write(odd, path, bits=bits, chunk_ids=100, block_ids=64)
    out = token_files.read(spark, path).orderBy("doc_id").collect()
    start = 0
    for r, d in zip(out, odd.orderBy("doc_id").collect(), strict=True):
        want = coder.library_ids(d.text or "") + array("I", [1]).tobytes()
        assert (r.doc_id, r.start, bytes(r.ids)) == (d.doc_id, start, want)
        start += len(want) // 4
    token_files.write(empty(spark), str(tmp_path / "none"))
    assert token_files.read(spark, str(tmp_path / "none")).count() == 0


def test_damaged_chunks_are_noticed():
    writer = token_files._Writer(0, False, 10, 8)
    writer.add(1, array("I", [1, 2, 3]).tobytes())
    row = writer.take()
    row["crc"] ^= 1
    with pytest.raises(ValueError, match="damaged"):
        token_files.read_chunk(row)


# 6 counts ------------------------------------------------------------------------------------------------------------


def test_trie_counts_equal_single_words(spark, odd):
    counter = token_counts.UnigramCounter.from_ranks(["▁", "a", "b", "ab", "▁a", "ba", "▁ab"])
    words = ["".join(p) for p in ["a", "b", "abab", "bbb", "aab", "xé", "ababab"]]
    alone = {w: counter.count_trie([w])[w] for w in words}
    assert counter.count_trie(words) == alone
    assert counter.count([" ".join(words), None, " \n"]) == [(7, sum(alone.values())), (0, 0), (0, 0)]
    out = {r.doc_id: r for r in token_counts.with_token_counts(odd).collect()}
    assert out[1].n_tokens == 0 and out[5].n_words == 30_000 and out[6].n_tokens == out[7].n_tokens
    assert token_counts.with_token_counts(empty(spark)).count() == 0


# 7 neighbours --------------------------------------------------------------------------------------------------------


def test_neighbours_against_brute_force(spark):
    rng = np.random.default_rng(3)
    base = rng.normal(size=(400, 16)).astype(np.float32)
    base[50:90] = base[50]  # ties
    rows = [(i, [float(x) for x in v]) for i, v in enumerate(base)]
    rows += [(1000, None), (1001, []), (1002, [0.0] * 16), (1003, [float("nan")] * 16), (1004, [None] * 16), (1005, [1.0] * 8)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = defaultdict(list)
    for r in neighbours.nearest(df, df.where("vec_id % 20 = 0"), 10, query_block=7, candidate_block=150).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.vec_id, r.score))
    wide = base.astype(float)
    for q in range(0, 400, 20):
        d = neighbours.euclidean(np.repeat(wide[q][None], 400, 0), wide)
        assert got[q] == [(i, d[i]) for i in np.lexsort((np.arange(400), d)) if i != q][:10]
    assert set(got) == set(range(0, 400, 20))
    assert neighbours.nearest(df.where("false"), df.where("false")).count() == 0
    few = df.where("vec_id < 3")
    assert neighbours.nearest(few, few).groupBy("query_id").count().select("count").distinct().first()[0] == 2


# 8 pages -------------------------------------------------------------------------------------------------------------


def test_pages(spark):
    page = """<html><head><title>t</title><style>x</style></head><body><header>Site <h1>Name</h1></header><nav><a href=x>menu</a></nav><div class="cookie-notice">We use cookies, a lot of them.</div>
    <article><h1>A &amp; B</h1><p title="a>b">First <b>bo</b>ld&nbsp;text, long enough to be the main text of this page for sure.<p>Two<br>lines<script>var a = "<p>no</p>"</script><div class=ad>Buy</div></article>
    <section class="comments"><p>Nice article that I liked very much indeed, thank you all.</section><aside>side</aside><footer>foot</footer>"""
    assert html_text.extract(page) == "A & B First bold text, long enough to be the main text of this page for sure. Two lines"
    rows = spark.createDataFrame([(1, "u", page, "e"), (2, None, None, None), (3, "u", "", None), (4, "u", "<p>short", None)], "page_id long, url string, html string, text string")
    out = {r.page_id: (r.text, r.n_chars) for r in html_text.with_main_text(rows).collect()}
    assert out[2] == out[3] == ("", 0) and out[4] == ("short", 5)
    assert html_text.extract("<form><div><p>A page inside a form, with enough text to be more than a form.</p></div></form>")
    assert html_text.main_span([0, 0, 100, 5, 0, 90, 0]) == (2, 6) and html_text.main_span([]) == (0, 0)


STORY = "The story goes on with many words that nobody has told before in this way. " * 3


@pytest.mark.parametrize("names", ["layout has-sidebar", "page with-sidebar", "search-results", "market-share", "side-by-side", "sidebar", "related"])
def test_wrappers_named_like_surroundings_keep_their_article(names):
    stray = "<p>A line that stands outside of the wrapper and is long enough to surge all alone on this page.</p>"
    page = f"""{stray}<div class="{names}"><div class="sidebar"><p>A box.</p></div><article><h1 class="related">Head</h1><p>{STORY}</p><section id="related-work"><h2>Related work</h2><p>Others.</p></section>
    <form>Search here</form><div class="ad">Buy</div><div class="comments"><p>{STORY}{STORY}{STORY}</p></div></article></div>{stray}"""
    assert html_text.extract(page) == f"Head {STORY}Related work Others."


def test_surroundings_by_name_and_attributes():
    for names in ("sidebar", "td-sidebar-left", "comments-area", "cookie-notice", "site-footer", "share_buttons", "ad-slot-3"):
        assert html_text.extract(f"<div><p>{STORY}</p></div><div class='{names}'><p>Beside it.</p></div><p>{STORY}</p>") == f"{STORY}{STORY}".strip()
    for shown in ("title='a hidden gem'", "class='not hidden at all'", "data-x='display:none'", "hidden=until-found"):
        assert "Gem." in html_text.extract(f"<article><p>{STORY}</p><div {shown}>Gem.</div></article>")
    for not_shown in ("hidden", "HIDDEN=''", "aria-hidden=true", "style='color:red; display : none'"):
        assert "Gem." not in html_text.extract(f"<article><p>{STORY}</p><div {not_shown}>Gem.</div></article>")


def test_article_in_a_form_beside_stray_text():
    stray = "<p>A line that stands outside of the form and is long enough to surge all alone on this page.</p>"
    page = f"{stray}<form><article><h1>Head</h1><p>{STORY}{STORY}</p><aside>Box</aside><form>Send</form></article></form>"
    assert html_text.extract(page) == f"Head {STORY}{STORY}".strip()


@pytest.mark.parametrize("tag", ["main", "div"])
def test_article_teasers_beside_a_main_text(tag):
    teaser = "<article><h2>Teaser</h2><p>It rained again in the town, more than it did in all the weeks before, so read on.</p></article>"
    got = html_text.extract(f"<body><{tag}><h1>Head</h1><p>{STORY}</p><p>{STORY}</p><p>{STORY}</p></{tag}>{teaser}{teaser}</body>")
    assert got.startswith(f"Head {STORY}{STORY}{STORY}".strip())
    assert tag == "div" or got == f"Head {STORY}{STORY}{STORY}".strip()


def test_self_closed_drawings_end_at_once():
    for drawing in ("<svg/>", "<svg class='x' />", "<math a=\"b\"/>"):
        assert html_text.extract(f"<p>{STORY}</p>{drawing}<p>{STORY}</p>") == f"{STORY}{STORY}".strip()
        assert html_text.extract(f"<p>{STORY}</p>{drawing}<p>Kept.</p><svg>gone</svg><p>{STORY}</p>") == f"{STORY}Kept. {STORY}".strip()
    assert html_text.extract(f"<p>{STORY}</p><svg href=a/>gone</svg>") == STORY.strip()


# 9 licenses ----------------------------------------------------------------------------------------------------------


def test_licenses_against_exact_search(spark, odd):
    rng = random.Random(9)
    words = "lorem ipsum dolor sit amet the license of software work under version".split()
    rows, planted = [], {}
    for i in range(120):
        parts = [rng.choice(words) for _ in range(rng.randrange(300))]
        name = rng.choice([None, *licenses.TEMPLATES])
        if name:
            parts.insert(rng.randrange(len(parts) + 1), licenses.TEMPLATES[name].upper() if i % 2 else licenses.TEMPLATES[name])
        planted[i] = name
        rows.append((i, " ".join(parts), "en", "s"))
    found = defaultdict(set)
    for r in licenses.scan(docs_of(spark, rows)).collect():
        found[r.doc_id].add(r.license)
        assert r.containment >= 0.8 and r.first_word < r.end_word
    for i, name in planted.items():
        assert name is None or name in found[i]
        assert not (found[i] - {name}) or {name, *found[i]} <= {"cc-by-4.0", "cc-by-sa-4.0", "all-rights-reserved", name}
    assert licenses.scan(odd).count() == 0 == licenses.scan(empty(spark)).count() == licenses.scan(odd, {}).count()


def found_licenses(text):
    return {r[0] for r in licenses.Scanner(licenses.known_licenses()).scan([None, "before it " + text + " and after it", ""])[1]}


@pytest.mark.parametrize(
    ("text", "want"),
    [
        ("Licensed under the MIT License.", "mit"),
        ("Available under the terms of the BSD 3-Clause License", "bsd-3-clause"),
        ("This is licensed under the GNU General Public License, version 2.", "gpl-2.0"),
        ("This work is licensed under the GNU General Public License, version 2.", "gpl-2.0"),
        ("This work is licensed under the GNU General Public License, version 3.", "gpl-3.0"),
        ("covered by the GNU Lesser General Public License v2.1", "lgpl-2.1"),
        ("distributed under the Mozilla Public License, v. 2.0", "mpl-2.0"),
        ("SPDX-License-Identifier: BSD-3-Clause", "bsd-3-clause"),
        ("// SPDX-License-Identifier: GPL-2.0-or-later", "gpl-2.0"),
        ("licensed under a Creative Commons Attribution-NonCommercial 4.0 International License", "cc-by-nc-4.0"),
        (licenses._gnu_notice("library", "Lesser", "2.1"), "lgpl-2.1"),
        (licenses._gnu_notice("program", "Affero", "3"), "agpl-3.0"),
        (licenses._gnu_notice("program", "", "2"), "gpl-2.0"),
        (licenses.TEXTS["apache-2.0"][0], "apache-2.0"),
        (licenses.TEXTS["isc"][0], "isc"),
        (licenses.TEXTS["0bsd"][0], "0bsd"),
    ],
)
def test_license_wordings_that_are_not_planted(text, want):
    assert found_licenses(text) == {want}


def test_licenses_without_their_telling_words():
    for text in ("under the GNU General Public License, version 4", "as the MIT professor said", "secondary licenses are the GNU Lesser General Public License, Version 2.1", "under the GNU General Public License", "einer License mit Folgen"):
        assert not found_licenses(text)


def test_full_license_texts():
    files = licenses._files()
    assert {"apache-2.0", "gpl-2.0", "gpl-3.0", "lgpl-2.1", "mpl-2.0"} <= set(files)
    for name, text in files.items():
        assert name in found_licenses(text)
        words = text.split()
        assert name in found_licenses(" ".join(w for i, w in enumerate(words) if i % 60 != 40) if name not in ("gpl-3.0", "lgpl-3.0") else text.upper())
    for name in ("bsd-2-clause", "bsd-3-clause"):
        assert found_licenses(licenses.TEXTS[name][0]) == {name, "bsd-text"}


# 10 mixing -----------------------------------------------------------------------------------------------------------


def test_mix_meets_targets(spark, odd):
    rng = random.Random(6)
    rows = [(i, " ".join(["w"] * rng.randrange(1, 60)), "en", rng.choice(["a", "a", "a", "b", "c", None])) for i in range(2000)]
    out = mixing.mix(docs_of(spark, rows)).collect()
    by = defaultdict(list)
    for r in out:
        by[r.source].append(r)
        assert 0 <= r.taken <= 2 * r.size and r.taken == r.copies * r.size
    total = sum(len(t.split()) for _, t, _, _ in rows)
    assert sum(v[0].target for v in by.values()) == pytest.approx(1.5 * total, rel=1e-6)
    for v in by.values():
        assert v[0].target <= 2 * v[0].source_size + 1e-6
        assert sum(r.taken for r in v) == pytest.approx(v[0].target, abs=2 * 60)
    again = {r.doc_id: r.taken for r in mixing.mix(docs_of(spark, rows).repartition(7)).collect()}
    assert again == {r.doc_id: r.taken for r in out}
    copies = mixing.repeat_copies(mixing.mix(odd), odd.columns)
    assert copies.columns == odd.columns and mixing.mix(empty(spark)).count() == 0


def brute_mix(rows, weights=(3, 1, 2), share=1.5, most=2):
    """(target, taken by doc_id) of (doc_id, size, source) rows: bisection on the dual, document by document, then the repair."""
    by = defaultdict(list)
    for i, n, s in rows:
        by[s].append((i, n))
    names = sorted(by, key=lambda s: (s is None, s or ""))
    held = {s: sum(n for _, n in by[s]) for s in names}
    weight = {s: weights[k % len(weights)] for k, s in enumerate(names)}
    budget, target, free = share * sum(held.values()), {}, list(names)
    while free:
        each = (budget - sum(target.values())) / sum(weight[s] for s in free)
        over = [s for s in free if weight[s] * each >= most * held[s]]
        target |= {s: most * held[s] for s in over} or {s: weight[s] * each for s in free}
        free = [s for s in free if s not in target]
    taken = {}
    for s in names:
        docs = sorted(((i, n) for i, n in by[s] if n), key=lambda x: (-x[1], -1 if x[0] is None else x[0] % 64, -1 if x[0] is None else x[0]))
        taken |= {i: 0 for i, n in by[s] if not n}
        if not docs:
            continue
        low, high = -50.0, math.log(most) / min(n for _, n in docs)
        rate = lambda at, n: math.exp(min(at * n, math.log(most)))
        for _ in range(200):
            at = (low + high) / 2
            low, high = (at, high) if sum(n * rate(at, n) for _, n in docs) < target[s] else (low, at)
        rates = [min(most * 1_000_000, int(rate(high, n) * 1_000_000 + 0.5)) for _, n in docs]
        ends = np.cumsum(rates)
        copies = (ends + 500_000) // 1_000_000 - (ends - rates + 500_000) // 1_000_000
        of_size = defaultdict(list)
        for (i, n), c in zip(docs, copies, strict=True):
            of_size[n].append((i, int(c)))
        miss = math.floor(target[s] + 0.5) - sum(n * c for n, v in of_size.items() for _, c in v)
        for n, v in of_size.items():
            all_copies = sum(c for _, c in v)
            while abs(miss) >= n and 0 <= all_copies + (1 if miss > 0 else -1) <= most * len(v):
                all_copies += 1 if miss > 0 else -1
                miss -= n if miss > 0 else -n
            for k, (i, _) in enumerate(v):
                taken[i] = n * (all_copies // len(v) + (k < all_copies % len(v)))
    return target, taken


@pytest.mark.parametrize("seed", [1, 2, 3])
def test_mix_against_brute_force(spark, seed):
    rng = random.Random(seed)
    rows = [(i, rng.choice([0, 1, 5, 5, 40, rng.randrange(1, 300), rng.randrange(1, 4000)]), rng.choice(["a", "a", "a", "b", "c", "d", None])) for i in range(700)]
    docs = spark.createDataFrame([(i, " ".join(["w"] * n) if n else rng.choice([None, "", " "]), s, 1, 2, 3) for i, n, s in rows], "doc_id long, text string, source string, parts int, earlier int, size int")
    target, taken = brute_mix(rows)
    out = mixing.mix(docs).collect()
    assert {r.doc_id: r.taken for r in out} == taken
    by = defaultdict(list)
    for r in out:
        assert (r.parts, r.earlier) == (1, 2) and r.target == pytest.approx(target[r.source], abs=1e-5)
        by[r.source].append(r)
    for s, v in by.items():
        assert abs(sum(r.taken for r in v) - target[s]) <= max(1, min(r.size for r in v if r.size))
        # Exponential tilt: below the largest rate, the logarithm of a rate is in proportion to the size.
        slopes = [math.log(r.rate) / r.size for r in v if 0.01 < r.rate < 1.999 and r.size > 20 and abs(math.log(r.rate)) > 0.01]
        assert not slopes or max(slopes) - min(slopes) <= 1e-3 * max(map(abs, slopes))


def test_mix_with_a_source_that_has_too_many_words(spark):
    rows = [(i, "w " * 50, "en", "big") for i in range(400)] + [(1000 + i, "w " * (1 + i % 7), "en", f"s{i % 5}") for i in range(100)]
    out = mixing.mix(docs_of(spark, rows), share=0.5).collect()
    big = [r for r in out if r.source == "big"]
    assert abs(sum(r.taken for r in big) - big[0].target) < 50 and 0 < sum(r.taken for r in big) < 400 * 50
    none = mixing.mix(docs_of(spark, [(1, None, "en", None), (2, " ", "en", "a")])).collect()
    assert [(r.taken, r.target) for r in none] == [(0, 0.0)] * 2


# pipeline ------------------------------------------------------------------------------------------------------------


def test_pipeline_stages(spark, tmp_path):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    docs = common.table(spark, sf, "documents")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = docs
        docs = common.materialise(stage(spark, docs, sf), f"test-{name}")
        assert docs.columns == columns
        assert docs.select("doc_id").subtract(before.select("doc_id")).count() == 0
    tokens = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert tokens.count() == docs.count()
    with open(bpe.vocabulary_path(), encoding="utf-8") as f:
        coder = bpe.ForcedBoundaryBpe(f.read())
    texts = {r.doc_id: r.text for r in docs.collect()}
    assert all(bytes(r.token_ids) == coder.library_ids(texts[r.doc_id]) for r in tokens.collect())


def test_rows_of_every_stage(spark, coder):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    docs = common.materialise(common.table(spark, sf, "documents").withColumn("extra", F.col("doc_id") * 2), "test-docs")
    stage = dict(corpus_pipeline.STAGES)
    ids = lambda df: sorted(r.doc_id for r in df.select("doc_id").collect())
    model = language.fit(docs.where(~language.held_out(F.col("doc_id"))).select("doc_id", "text", "lang"))
    told = language.predict(docs, model).collect()
    kept = common.materialise(stage["language"](spark, docs, sf), "test-language")
    assert ids(kept) == sorted(r.doc_id for r in told if r.lang_pred != "und" and r.score >= 0.25) and ids(kept)

    rules = quality.fit(kept, common.table(spark, sf, "labels"))
    want = []
    for r in quality.with_statistics(kept).collect():
        n_words, _, _, _, n_repeat = brute_statistics(r.text)
        values = {k: float(v or 0) for k, v in r.asDict().items() if k in quality.STATS}
        if n_words >= 10 and 100 * n_repeat <= 20 * n_words and not any(all(t.holds(values) for t in rule) for rule in rules):
            want.append(r.doc_id)
    good = common.materialise(stage["quality"](spark, kept, sf), "test-quality")
    assert ids(good) == sorted(want) and want

    rows = [(r.doc_id, r.text) for r in good.collect()]
    found = brute_components(rows, 5, 80)
    alone = common.materialise(stage["near_duplicates"](spark, good, sf), "test-alone")
    assert ids(alone) == sorted(i for i, (_, component) in found.items() if i == component)

    copies = {r.doc_id: r.copies if r.size else 1 for r in mixing.mix(alone).collect()}
    mixed = common.materialise(stage["mixing"](spark, alone, sf), "test-mixed")
    assert Counter(ids(mixed)) == Counter({i: n for i, n in copies.items() if n})

    texts = {r.doc_id: r.text for r in mixed.collect()}
    out = stage["tokens"](spark, mixed, sf)
    assert out.columns == [*(c for c in docs.columns if c != "text"), "n_tokens", "token_ids", "decoded"]
    for r in out.collect():
        want_ids = coder.library_ids(texts[r.doc_id])
        assert bytes(r.token_ids) == want_ids and r.decoded == coder.decode(want_ids) and r.n_tokens == len(want_ids) // 4 and r.extra == 2 * r.doc_id


def test_crc_marks_held_out(spark):
    rows = spark.range(100).select("id", language.held_out(F.col("id")).alias("h")).collect()
    assert all(r.h == (zlib.crc32(str(r.id).encode()) % 4 == 2) for r in rows)
