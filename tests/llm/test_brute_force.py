"""Every operator's registered path against plain Python, and the odd tables that the first test module leaves out."""

import hashlib
import html as html_entities
import itertools
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
SF = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string"


@pytest.fixture(scope="module")
def coder():
    with open(bpe.vocabulary_path(), encoding="utf-8") as f:
        return bpe.ForcedBoundaryBpe(f.read())


@pytest.fixture(scope="module")
def clashing(spark):
    """Nulls in every column, repeated rows, a null and a repeated doc_id, and columns named like those of the operators' results."""
    rng = random.Random(12)
    words = [rng.choice("abcdefghij") * rng.randrange(1, 6) for _ in range(400)]
    rows = [(1, " ".join(words), "en", "a"), (1, " ".join(words), "en", "a"), (2, None, None, None), (None, "a b c d", "fr", "b"), (None, None, None, None), (3, "", "en", None), (4, " ".join(words[:-1]), "en", "b"), (5, "x " * 30_000, "en", "a")]
    extra = ("n_words", "kept", "rule", "n_shingles", "component_id", "lang_pred", "score", "n_tokens", "token_ids", "decoded", "size", "taken", "copies", "target", "rate", "source_size", "parts", "earlier", "smaller", "_mix", "_w", "sig", "v", "place", "deal")
    kind = DOCS + "".join(f", `{c}` int" for c in extra)
    return spark.createDataFrame([(*r, *range(len(extra))) for r in rows], kind)


def write_tables(folder, **tables):
    for name, df in tables.items():
        df.write.parquet(f"{folder}/{name}.parquet")
    return str(folder)


# 1 quality -----------------------------------------------------------------------------------------------------------


def test_quality_on_clashing_and_empty_tables(spark, clashing, tmp_path):
    labels = spark.createDataFrame([(1, 0, 0), (1, 1, 0), (4, 1, 0), (None, 0, 0)], "doc_id long, quality int, toxic int")
    rules = quality.fit(clashing, labels)
    out = quality.judge(clashing, rules)
    assert out.count() == clashing.count() and out.where("n_words IS NULL OR kept IS NULL").count() == 0
    for docs, marks in ((clashing.where("false"), labels), (clashing, labels.where("false")), (clashing.where("false"), labels.where("false"))):
        assert quality.fit(docs, marks) == []
    at = write_tables(tmp_path, documents=clashing.select("doc_id", "text", "lang", "source"), labels=labels)
    assert quality.op1_quality_rules(spark, at).count() == clashing.count()


def test_a_document_labelled_both_ways_is_bad(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(quality, "learn_rules", lambda rows: seen.append({r["doc_id"]: r["bad"] for r in rows}) or [])
    docs = spark.createDataFrame([(i, f"w{i} " + "a b c d e f g h i j k l") for i in range(4)], "doc_id long, text string")
    for order in (0, 1):
        labels = spark.createDataFrame([(0, order), (0, 1 - order), (1, 1), (2, 0)], "doc_id long, quality int")
        quality.fit(docs, labels)
    assert seen == [{0: True, 1: False, 2: True}] * 2


def test_learned_list_against_row_by_row_rules(spark):
    docs = common.table(spark, SF, "documents")
    rules = quality.fit(docs, common.table(spark, SF, "labels")) or [(quality.Test("symbol_share", True, 0.01),), (quality.Test("n_words", False, 40.0), quality.Test("capital_share", True, 0.02))]
    for r in quality.judge(docs, rules).collect():
        first = next((k for k, rule in enumerate(rules, 1) if all(t.holds(r.asDict()) for t in rule)), 0)
        assert r.rule == first and r.kept == (not r.base_failed and first == 0)


# 2 near duplicates ---------------------------------------------------------------------------------------------------


def test_null_and_repeated_ids_have_their_set_sizes(spark, clashing):
    out = near_dup.link(clashing, 3, 85).collect()
    assert Counter((r.doc_id, r.n_shingles) for r in out) == Counter({(1, 398): 2, (2, 0): 1, (None, 2): 1, (None, 0): 1, (3, 0): 1, (4, 397): 1, (5, 1): 1})
    assert all(r.kept and r.component_id is None for r in out if r.doc_id is None)
    assert {r.doc_id: r.component_id for r in out if r.doc_id} == {1: 1, 2: 2, 3: 3, 4: 1, 5: 5}


def test_word_hashes_do_not_depend_on_place_or_blocks(monkeypatch):
    rng = random.Random(1)
    words = ["".join(rng.choice("abcXYZé日\x1c\x85") for _ in range(rng.randrange(1, 12))) for _ in range(3000)] + ["L" * 5000]
    text = "".join(w + rng.choice(" \t\n\x0b\x0c\r  ") for w in words)
    lower = [re.sub("[A-Z]", lambda m: m[0].lower(), w) for w in words]
    whole = near_dup.word_hashes(text.encode())
    assert len(whole) == len(words) and len(set(whole.tolist())) == len(set(lower))
    by_word = {}
    assert all(by_word.setdefault(w, h) == h for w, h in zip(lower, whole.tolist(), strict=True))
    monkeypatch.setattr(near_dup, "WORD_BLOCK", 64)
    assert (near_dup.word_hashes(text.encode()) == whole).all() and (near_dup.word_hashes(b"  " + text.encode() + b"\n") == whole).all()
    assert not len(near_dup.word_hashes(b"")) and not len(near_dup.word_hashes(b" \n"))


def test_frequent_values_beyond_the_bound_stay_in_lists(spark, monkeypatch):
    counts = spark.createDataFrame([(v, 10 + v) for v in range(200)], "v long, times long")
    assert near_dup._most_frequent(counts).tolist() == list(range(200))
    monkeypatch.setattr(near_dup, "HOT_MOST", 50)
    kept = near_dup._most_frequent(counts).tolist()
    assert 0 < len(kept) <= 50 and kept == list(range(200 - len(kept), 200))
    # Links do not depend on it.
    monkeypatch.setattr(near_dup, "HOT_LEAST", 3)
    monkeypatch.setattr(near_dup, "HOT_MOST", 2)
    rng = random.Random(9)
    base = [f"w{rng.randrange(500)}" for _ in range(80)]
    rows = [(i, " ".join(w if rng.random() > 0.02 else f"x{rng.randrange(99)}" for w in base)) for i in range(25)]
    from test_operators import brute_components

    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dup.link(spark.createDataFrame(rows, "doc_id long, text string"), 3, 85).collect()}
    assert got == brute_components(rows, 3, 85)


def test_large_classes_and_families(spark, monkeypatch):
    """A class of copies and a family with a hub, both far above the bound for a key that is joined by shuffle."""
    monkeypatch.setattr(near_dup, "HOT_LEAST", 5)
    rng = random.Random(3)
    text = lambda: [f"w{rng.randrange(5000)}" for _ in range(100)]
    copied, base = text(), text()
    rows = [(i, " ".join(copied)) for i in range(40)]
    for i in range(100, 140):
        near = list(base)
        near[rng.randrange(100)] = f"x{i}"
        rows.append((i, " ".join(near)))
    rows += [(200 + i, " ".join(text())) for i in range(10)]
    out = {r.doc_id: r.component_id for r in near_dup.link(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {out[i] for i in range(40)} == {0} and {out[i] for i in range(100, 140)} == {100} and all(out[200 + i] == 200 + i for i in range(10))


# 3 language ----------------------------------------------------------------------------------------------------------


def plain_grams(text, orders=language.NGRAM):
    letters = "".join(c if c.isalpha() else "\0" for c in text.lower())
    letters = "\0" + re.sub("\0+", "\0", letters) + "\0"
    return [letters[i : i + n] for n in orders for i in range(len(letters) - n + 1)]


def test_language_against_exact_sets(spark):
    """The filter may add false positives to exact n-gram sets, never lose one; its corrected shares follow theirs."""
    docs = common.table(spark, SF, "documents")
    learned = docs.where(~language.held_out(F.col("doc_id"))).where("lang IS NOT NULL AND text IS NOT NULL")
    model = language.fit(learned)
    seen, sizes = defaultdict(Counter), Counter()
    for r in learned.collect():
        seen[r.lang].update(set(plain_grams(r.text)))
        sizes[r.lang] += 1
    exact = {g: {x for x, n in seen[g].items() if n >= max(2, math.ceil(sizes[g] * 0.02))} for g in sizes}
    assert model.languages == sorted(exact)
    rates = model.false_rates()
    for r in language.predict(docs, model).collect():
        grams = plain_grams(r.text or "")
        if not any(c.isalpha() for c in r.text or ""):
            assert (r.lang_pred, r.score) == ("und", 0)
            continue
        share = {g: sum(x in exact[g] for x in grams) / len(grams) for g in exact}
        assert abs(r.score - max(share.values())) <= 0.02
        assert share[r.lang_pred] >= max(share.values()) - 0.02
    letters = np.concatenate((np.zeros(1, np.uint32), language._letters("hello world"), np.zeros(1, np.uint32)))
    for k, g in enumerate(model.languages):
        hits = sum(int(model.hits(language.ngram_hashes(letters, n))[k]) for n in language.NGRAM)
        assert hits >= sum(x in exact[g] for x in plain_grams("hello world"))
    assert (rates < 0.5).all()


def test_language_ties_and_clashing_names(spark, clashing):
    twin = "alpha beta gamma delta"
    rows = [(i, twin, lang, "s") for i, lang in enumerate(["bb", "aa"] * 4)]
    model = language.fit(spark.createDataFrame(rows, DOCS))
    told = language.predict(spark.createDataFrame(rows, DOCS), model).collect()
    assert {r.lang_pred for r in told} == {"aa"}
    out = language.predict(clashing, model)
    assert out.columns.count("lang_pred") == 1 and out.columns.count("score") == 1 and out.count() == clashing.count()
    assert language.predict(clashing.where("false"), model).count() == 0
    # Rows that share a doc_id but not a language do not mix.
    mixed = spark.createDataFrame([(1, "uno dos tres cuatro", "es", "s"), (1, "one two three four", "en", "s"), (2, "uno dos tres cuatro", "es", "s"), (2, "one two three four", "en", "s")], DOCS)
    told = language.predict(mixed, language.fit(mixed)).collect()
    assert all(r.lang == r.lang_pred for r in told)


def test_languages_beyond_the_bound_are_those_with_fewest_texts(spark, monkeypatch):
    monkeypatch.setattr(language, "MOST_LANGUAGES", 2)
    rows = [(i, f"text {i}", g, "s") for i, g in enumerate(["aa"] * 3 + ["bb"] * 2 + ["cc"])]
    assert language.fit(spark.createDataFrame(rows, DOCS)).languages == ["aa", "bb"]


# 4, 5 tokens ---------------------------------------------------------------------------------------------------------


def library_rows(coder, docs):
    library = coder.library()
    for r in docs.collect():
        ids = library.encode(r.text or "", add_special_tokens=False).ids
        yield r.doc_id, array("I", ids), library.decode(ids, skip_special_tokens=False)


def test_digests_of_the_registered_path(spark, coder, clashing, tmp_path):
    at = write_tables(tmp_path, documents=clashing)
    for folder in (SF, at):
        want = Counter((i, len(ids), hashlib.sha256(ids.tobytes()).hexdigest(), hashlib.sha256(text.encode()).hexdigest()) for i, ids, text in library_rows(coder, common.table(spark, folder, "documents")))
        assert Counter(map(tuple, bpe.op4_bpe_codec(spark, folder).collect())) == want
    coded = bpe.encoded(clashing)
    assert coded.columns == [*(c for c in clashing.columns if c not in ("text", "n_tokens", "token_ids", "decoded")), "n_tokens", "token_ids", "decoded"]
    assert coded.count() == clashing.count() and bpe.digests(clashing.where("false")).count() == 0
    assert {(r.doc_id, r.n_tokens) for r in coded.collect()} == {(i, len(ids)) for i, ids, _ in library_rows(coder, clashing)}


def test_small_caches_change_no_ids(monkeypatch, coder):
    with open(bpe.vocabulary_path(), encoding="utf-8") as f:
        monkeypatch.setattr(bpe, "CHUNK_ENTRIES", 3)
        monkeypatch.setattr(bpe, "CACHE_ENTRIES", 2)
        monkeypatch.setattr(bpe, "LIBRARY_ENTRIES", 3)
        small = bpe.ForcedBoundaryBpe(f.read())
    rng = random.Random(7)
    for _ in range(300):
        text = " ".join(rng.choice(["the", "thonatst.", "Ing,", "it's", "qzxj", "a1b2", "é!é", "of"]) for _ in range(12))
        assert small.encode(text) == coder.encode(text) == small.library_ids(text)


@pytest.mark.parametrize("size", [1, 23, 24, 25, 300])
def test_short_and_long_fragments_merge_alike(coder, monkeypatch, size):
    rng = random.Random(size)
    for _ in range(40):
        word = "".join(rng.choice("thearonis") for _ in range(size))
        short = [coder.merge(word, last) for last in (False, True)]
        monkeypatch.setattr(bpe, "SHORT", 10**6)
        assert [coder.merge(word, last) for last in (False, True)] == short
        monkeypatch.setattr(bpe, "SHORT", 0)
        assert [coder.merge(word, last) for last in (False, True)] == short
        monkeypatch.setattr(bpe, "SHORT", 24)


def test_token_files_of_the_registered_path(spark, coder, tmp_path):
    rows = list(library_rows(coder, common.table(spark, SF, "documents").orderBy("doc_id")))
    start, want = 0, []
    for i, ids, _ in rows:
        ids.append(1)
        want.append((i, start, len(ids), zlib.crc32(ids.tobytes())))
        start += len(ids)
    assert sorted(map(tuple, token_files.op5_token_files(spark, SF).collect())) == sorted(want)


def test_token_files_of_null_and_repeated_ids(spark, coder, clashing, tmp_path):
    path = str(tmp_path / "files")
    token_files.write(clashing, path, chunk_ids=50, block_ids=16)
    out = token_files.read(spark, path).collect()
    key = lambda i, t: (i is not None, i or 0, t is not None, t or "")
    ordered = sorted(((r.doc_id, r.text) for r in clashing.collect()), key=lambda x: key(*x))
    start = 0
    for r, (i, text) in zip(sorted(out, key=lambda r: r.start), ordered, strict=True):
        want = coder.library_ids(text or "") + array("I", [1]).tobytes()
        assert (r.doc_id, r.start, bytes(r.ids)) == (i, start, want)
        start += len(want) // 4


# 6 token counts ------------------------------------------------------------------------------------------------------


def enumerated(word, scores, unknown):
    """(score, tokens) of the best segmentation, by enumerating them all."""
    best = (-math.inf, 0)
    for cuts in itertools.product((False, True), repeat=len(word) - 1):
        parts, at = [], 0
        for i, cut in enumerate(cuts, 1):
            if cut:
                parts.append(word[at:i])
                at = i
        parts.append(word[at:])
        for ways in itertools.product(*[([(scores[p], 1)] if p in scores else []) + [(len(p.encode()) * unknown, len(p.encode()))] * (len(p) == 1) for p in parts]):
            total = (sum(w[0] for w in ways), sum(w[1] for w in ways))
            if total[0] > best[0] + 1e-12 or abs(total[0] - best[0]) <= 1e-12 and total[1] < best[1]:
                best = total
    return best


def test_counts_against_enumerated_segmentations():
    rng = random.Random(6)
    for _ in range(30):
        pieces = ["▁", *{"".join(rng.choice("ab") for _ in range(rng.randrange(1, 4))) for _ in range(6)}, "▁a", "▁ab", "é"]
        rng.shuffle(pieces)
        counter = token_counts.UnigramCounter.from_ranks(pieces)
        scores = {p: -math.log(k + token_counts.SHIFT) for k, p in enumerate(pieces)}
        words = ["".join(rng.choice("abé日") for _ in range(rng.randrange(1, 8))) for _ in range(12)]
        found = counter.count_trie(dict.fromkeys(words))
        for w in words:
            assert found[w] == enumerated("▁" + w, scores, counter.unknown)[1]


def test_words_longer_than_the_trie_go_on_from_its_scores(monkeypatch):
    counter = token_counts.UnigramCounter.from_ranks(["▁", "a", "b", "ab", "▁a", "ba", "▁ab"])
    words = ["ab" * 50 + tail for tail in ("", "a", "bb", "é")]
    deep = counter.count_trie(words)
    monkeypatch.setattr(token_counts, "SHARED", 5)
    assert counter.count_trie(words) == deep


def test_counts_of_clashing_tables(spark, clashing):
    out = token_counts.with_token_counts(clashing)
    assert out.columns.count("n_tokens") == 1 and out.where("n_tokens IS NULL").count() == 0
    assert {(r.doc_id, r.n_words) for r in out.collect()} == {(r.doc_id, len(WORD.findall(r.text or ""))) for r in clashing.collect()}


# 7 neighbours --------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("block", [4, 1000])
def test_neighbours_with_repeated_ids(spark, block):
    rng = np.random.default_rng(5)
    rows = [(i, [float(x) for x in rng.normal(size=8)]) for i in range(60)]
    rows += [rows[0], rows[0], rows[7], (0, [float(x) for x in rng.normal(size=8)]), (11, [float(x) for x in rng.normal(size=8)]), (12, rows[13][1])]
    df = spark.createDataFrame([(i, [float(np.float32(x)) for x in v], "e") for i, v in rows], "vec_id long, embedding array<float>, score string")
    got = defaultdict(list)
    for r in neighbours.nearest(df, df.where("vec_id % 5 = 0"), 10, query_block=block, candidate_block=block).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.rank, r.vec_id, r.score))
    vectors = [(i, np.float32(v).astype(float)) for i, v in rows]
    for q in range(0, 60, 5):
        nearest = {}
        for i, v in vectors:
            for j, w in vectors:
                if i == q and j != q:
                    d = float(neighbours.euclidean(v[None], w[None])[0])
                    nearest[j] = min(d, nearest.get(j, math.inf))
        want = sorted((d, j) for j, d in nearest.items())[:10]
        assert got[q] == [(k, j, d) for k, (d, j) in enumerate(want, 1)]


# 8 pages -------------------------------------------------------------------------------------------------------------


def plain_span(weights, window=html_text.WINDOW, surge=html_text.SURGE, beside=html_text.BESIDE):
    """Main span by the definition: lines are grouped where no window between them is empty, heavy groups beside the heaviest are kept."""
    n = len(weights)
    groups = []
    for i in (i for i in range(n) if weights[i]):
        if groups and not any(not any(weights[a : a + window]) for a in range(groups[-1][-1] + 1, i)):
            groups[-1].append(i)
        else:
            groups.append([i])

    def heaviest(group):
        return max(sum(weights[a : a + window]) for a in range(max(0, group[0] - window + 1), group[-1] + 1))

    heavy = [g for g in groups if heaviest(g) >= surge]
    if not heavy and groups:
        heavy = [max(groups, key=lambda g: (heaviest(g), -g[0]))]
    if not heavy:
        return 0, 0
    most = max(sum(weights[i] for i in g) for g in heavy)
    kept = [g for g in heavy if sum(weights[i] for i in g) >= beside * most]
    return kept[0][0], kept[-1][-1] + 1


@pytest.mark.parametrize("seed", range(8))
def test_surge_and_dive_against_the_definition(seed):
    rng = random.Random(seed)
    for _ in range(400):
        weights = [rng.choice([0, 0, 0, 0, 5, 30, 90, 400]) for _ in range(rng.randrange(24))]
        assert html_text.main_span(weights) == plain_span(weights), weights


def sentence(rng, n):
    return " ".join(rng.choice("the of and story water under many words were told again before".split()) for _ in range(n))


@pytest.mark.parametrize("seed", range(6))
def test_pages_without_article_marks(seed):
    """Menus, adverts and notices before, inside and after a text that nothing marks: only the line blocks can tell it."""
    rng = random.Random(seed)
    links = lambda n: "".join(f"<li><a href='/{i}'>{sentence(rng, 3)}</a></li>" for i in range(n))
    body = [sentence(rng, 6)] + [sentence(rng, rng.choice([3, 20, 40, 60])) for _ in range(8)] + [sentence(rng, 30)]
    noise = ["<nav><ul>" + links(5) + "</ul></nav>", f"<div class='ad'>{sentence(rng, 8)}</div>", f"<form>{sentence(rng, 5)}<input></form>", f"<script>var x = '{sentence(rng, 90)}'</script>", "<ul>" + links(6) + "</ul>"]
    parts = [f"<h1>{body[0]}</h1>"] + [f"<p>{p}</p>" for p in body[1:]]
    for extra in rng.sample(noise[:4], 2):
        parts.insert(rng.randrange(2, len(parts) - 1), extra)
    teaser = f"<p>{sentence(rng, 4)}</p>"
    page = f"<html><body>{teaser}{noise[0]}{noise[4]}<div>{''.join(parts)}</div><ul>{links(7)}</ul>{teaser}<footer>{sentence(rng, 60)}</footer></body></html>"
    assert html_text.extract(page) == " ".join(body)


def test_lines_beside_the_text_are_left_by_the_dive():
    """Short lines that stand apart from the text, with no element or name to tell them, are outside the surge and the dive."""
    rng = random.Random(3)
    body = [sentence(rng, 40) for _ in range(5)]
    apart = "<ul>" + "".join(f"<li><a href=x>{sentence(rng, 2)}</a>" for _ in range(4)) + "</ul>"
    page = f"<div>{sentence(rng, 5)}</div>{apart}" + "".join(f"<p>{p}</p>" for p in body) + f"{apart}<div>{sentence(rng, 6)}</div>{apart}<div>{sentence(rng, 4)}</div>"
    assert html_text.extract(page) == " ".join(body)


def test_article_marks_decide_few_pages(spark):
    """With article and main renamed, nearly all given pages give the same text: the line blocks find it, not the marks."""
    pages = [r.html for folder in ("sf0.001", "sf0.01") for r in common.table(spark, f"/root/testdata/{folder}", "pages").select("html").collect()]
    plain = [re.sub(r"(</?)(article|main)(?=[\s>])", r"\1div", p) for p in pages]
    assert sum(html_text.extract(a) == html_text.extract(b) for a, b in zip(pages, plain, strict=True)) >= 0.99 * len(pages)


def test_given_pages_keep_their_whole_article(spark):
    """The text between the article's tags, without adverts, in plain Python."""
    for r in common.table(spark, SF, "pages").collect():
        inner = re.search(r"<article>(.*)</article>", r.html, re.S)[1]
        inner = re.sub(r"<(script|style|form|aside|nav)\b.*?</\1>|<div class=\"[^\"]*\">.*?</div>|<!--.*?-->", "\n", inner, flags=re.S)
        blocks = re.split(r"</?(?:p|h1|h2|h3|br|li|ul|ol|div|blockquote|table|tr|td|section|pre)\b[^>]*>", inner)
        text = " ".join(" ".join(html_entities.unescape(re.sub(r"<[^>]+>", "", b)).split()) for b in blocks)
        assert html_text.extract(r.html) == " ".join(text.split())


def test_pages_with_odd_columns(spark):
    page = f"<p>{sentence(random.Random(1), 40)}</p>"
    long = "<div>" + page * 4000 + "</div>"
    rows = [(1, "u", page, 1, "x"), (1, "u", page, 1, "x"), (None, None, None, None, None), (2, "u", long, 2, "y")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, n_chars int, text string")
    out = html_text.with_main_text(df).collect()
    assert Counter(r.n_chars for r in out)[len(html_text.extract(page))] == 2 and any(r.text == "" for r in out)
    assert html_text.with_main_text(df.where("false")).count() == 0


# 9 licenses ----------------------------------------------------------------------------------------------------------


def sliding(text, template, need=licenses.CONTAINMENT):
    """Whether a window of the template's reach holds enough of its shingles, position by position."""
    clean = lambda t: t.lower().translate(str.maketrans("", "", licenses._DROPPED.decode())).split()
    words, own = clean(text), clean(template)
    width = min(licenses.WIDTH, len(own))
    grams = {tuple(own[i : i + width]) for i in range(len(own) - width + 1)}
    reach = len(own) - width + 1 + (len(own) // 2 if len(own) > width else 0)
    least = len(grams) if len(own) < licenses.WHOLE_WORDS else math.ceil(need * len(grams) - 1e-9)
    hits = [tuple(words[i : i + width]) for i in range(len(words) - width + 1)]
    return any(len({g for g in hits[a : a + reach] if g in grams}) >= least for a in range(len(hits)))


def test_licenses_against_sliding_windows(spark):
    rng = random.Random(4)
    template = " ".join(rng.choice("software copy grant permission notice terms work person free charge use".split()) for _ in range(60))
    words, rows = template.split(), []
    for i in range(150):
        inner = list(words)
        for _ in range(rng.randrange(6)):
            inner[rng.randrange(len(inner))] = "changed"
        for _ in range(rng.randrange(4)):
            inner.insert(rng.randrange(len(inner)), "added words here")
        if rng.random() < 0.2:
            inner = inner[: rng.randrange(20, 60)]
        rows.append((i, sentence(rng, rng.randrange(80)) + " " + " ".join(inner) + " " + sentence(rng, rng.randrange(80)), "en", "s"))
    rows.append((999, None, None, None))
    docs = spark.createDataFrame(rows + rows[:3], DOCS).withColumn("license", F.lit(1)).withColumn("containment", F.lit("x"))
    found = licenses.scan(docs, {"t": template}).collect()
    want = {i for i, t, _, _ in rows if t and sliding(t, template)}
    assert {r.doc_id for r in found} == want and 20 < len(want) < 150
    # Repeated rows match alike.
    assert all(sum(r.doc_id == i for r in found) % 2 == 0 for i in (0, 1, 2))


def test_band_settings_guarantee_retrieval():
    templates = licenses.prepare(licenses.known_licenses())
    for t in templates:
        assert t.miss_chance <= 1e-12 and (t.miss_chance == 0 or len(t.shingles) > 100), (t.name, len(t.shingles), len(t.bands), t.miss_chance)
    assert sum(t.miss_chance == 0 for t in templates) > 0.9 * len(templates)


@pytest.mark.parametrize("seed", range(4))
def test_misaligned_windows_of_just_enough_containment_retrieve(seed):
    """A fifth of the shingles lacking, at any place of a longer text: the window that holds the match retrieves the template."""
    rng = random.Random(seed)
    for size in (15, 60, 200, 900):
        words = [f"w{rng.randrange(10_000)}" for _ in range(size)]
        scanner = licenses.Scanner({"t": " ".join(words)})
        t = scanner.templates[0]
        for _ in range(20):
            inner, lacking = list(words), len(t.shingles) - t.need
            # A word that is changed takes five shingles with it.
            for at in rng.sample(range(2, size - 2), lacking // 5):
                inner[at] = "changed"
            text = [f"x{rng.randrange(99)}" for _ in range(rng.randrange(3 * size))] + inner + [f"y{rng.randrange(99)}" for _ in range(rng.randrange(3 * size))]
            assert [r[0] for r in scanner.scan([" ".join(text)])[0]] == ["t"]


def test_two_licenses_of_equal_wording_are_both_found():
    text = "Permission to use copy and change this work is given to all persons without any charge or other condition at all."
    rows = licenses.Scanner({"b": text, "a": text}).scan([text])[0]
    assert [r[0] for r in rows] == ["a", "b"] and {r[1:] for r in rows} == {(0, len(text.split()), 1.0)}


# 10 mixing -----------------------------------------------------------------------------------------------------------


def test_mixing_of_clashing_and_empty_tables(spark, clashing):
    out = mixing.mix(clashing)
    kept = [c for c in clashing.columns if c not in mixing.ADDED]
    assert out.columns == [*kept, *mixing.ADDED] and out.count() == clashing.count()
    for r in out.collect():
        assert (r.parts, r.smaller, r.earlier) == tuple(clashing.columns.index(c) - 4 for c in ("parts", "smaller", "earlier"))
        assert r.size == len(WORD.findall(r.text or "")) and r.taken == r.size * r.copies and r.taken <= 2 * r.size
    assert mixing.mix(clashing.where("false")).columns == out.columns and mixing.mix(clashing.where("false")).count() == 0
    copies = mixing.repeat_copies(out, ["doc_id", "text"])
    assert copies.count() == sum(r.copies if r.size else 1 for r in out.collect())


def test_newton_meets_a_plain_bisection():
    rng = np.random.default_rng(2)
    for _ in range(200):
        size = np.unique(rng.integers(1, 10 ** rng.integers(1, 6), 30))[::-1]
        n = rng.integers(1, 1000, len(size))
        whole = float((n * size).sum())
        target = whole * rng.choice([0.001, 0.3, 0.99, 1.0, 1.01, 1.7, 1.999])
        at = mixing.balance(size, n, target, 2)
        reached = (n * size * np.exp(np.minimum(at * size, math.log(2)))).sum()
        assert reached == pytest.approx(target, rel=1e-9)
    assert np.exp(mixing.balance(np.array([7, 3]), np.array([1, 1]), 20.0, 2) * 3) == pytest.approx(2)


# pipeline ------------------------------------------------------------------------------------------------------------


def test_pipeline_of_odd_tables(spark, tmp_path):
    import corpus_pipeline

    given = common.table(spark, SF, "documents").limit(60)
    odd = spark.createDataFrame([(10_001, None, "en", "a", 0), (10_002, "", None, None, 0), (None, "12 34 !!", None, "a", 8), (None, None, None, None, None)], given.schema)
    first = given.limit(5)
    docs = given.unionByName(odd).unionByName(first).withColumn("score", F.lit("own")).withColumn("kept", F.lit(7)).withColumn("size", F.lit(1))
    at = write_tables(tmp_path / "some", documents=docs, labels=common.table(spark, SF, "labels"))
    out = corpus_pipeline.run(spark, at)
    assert out.columns == [*(c for c in docs.columns if c != "text"), "n_tokens", "token_ids", "decoded"]
    rows = out.collect()
    assert rows and all(r.score == "own" and r.kept == 7 and r.size == 1 for r in rows) and not {10_001, 10_002} & {r.doc_id for r in rows}
    none = write_tables(tmp_path / "none", documents=docs.where("false"), labels=common.table(spark, SF, "labels").where("false"))
    assert corpus_pipeline.run(spark, none).count() == 0
