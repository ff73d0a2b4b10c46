"""The text operators against brute force, public libraries and edge cases."""

import hashlib
import random
import re
from collections import Counter

import pytest
from oracle import compare
from pyspark.sql import functions as F

from localcoef.llm import language, lines, neardup, substrings
from localcoef.llm.automaton import SuffixAutomaton
from localcoef.llm.bpe import encode_documents
from localcoef.llm.chat import PROBE, digest, format_examples, read_turns
from localcoef.llm.counts import BestPathCounter, count_tokens, read_pieces
from localcoef.llm.decontam import Tiling, contamination, tiles
from localcoef.llm.quality import score_quality
from localcoef.llm.queries import BYTE_BPE, ORACLE_SQL, PIECE_BPE, QUERIES, vocabulary
from localcoef.llm.wrappers import container, extract, extract_pages, infer

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, kept boolean, id long, key int, words string, marks string, n_words long, component string, `row` string"


def table(spark, texts, langs=None, ids=None):
    """Rows whose further columns have names that operators use inside."""
    n = len(texts)
    rows = [((ids or range(n))[i], texts[i], (langs or ["en"] * n)[i], "s", len(texts[i] or ""), True, 1, 2, "w", "m", 3, "c", "r") for i in range(n)]
    return spark.createDataFrame(rows, SCHEMA)


def prose(seed, n, size=400):
    r = random.Random(seed)
    return [r.choice("abcdefghij") + str(r.randrange(size)) for _ in range(n)]


def odd_texts():
    same = " ".join(prose(1, 90))
    return [None, "", "  \n \n", "one", same, same, same.upper(), " ".join(prose(2, 20000)), "\x1c\x1d  x\x85y", "é🙂 日本語 <|endoftext|> a", "a a a a " * 60, "l1\nl2\nl3\nl4", "x\nl1\nl2\nl3\ny", "l1\nl2\nl3"]


def test_quality_measures_and_edges(spark):
    texts = odd_texts()
    got = {r["doc_id"]: r for r in score_quality(table(spark, texts)).collect()}
    assert len(got) == len(texts)
    for i, t in enumerate(texts):
        w = WORD.findall(t or "")
        grams = Counter(tuple(w[k : k + 3]) for k in range(len(w) - 2))
        covered = {p for k in range(len(w) - 2) if grams[tuple(w[k : k + 3])] > 1 for p in (k, k + 1, k + 2)}
        assert (got[i]["n_words"], got[i]["n_repeat_words"], got[i]["word_chars"]) == (len(w), len(covered), sum(map(len, w))), i
        assert got[i]["base_failed"] == (len(w) < 50 or 100 * len(covered) > 50 * len(w))
    assert got[4]["kept"] and not got[10]["kept"] and not got[0]["kept"]
    assert score_quality(table(spark, []).limit(0)).count() == 0


def runs_by_force(texts, width):
    words = [WORD.findall(t or "") for t in texts]
    seen = Counter(tuple(w[i : i + width]) for w in words for i in range(len(w) - width + 1))
    out = []
    for w in words:
        gone = {p for i in range(len(w) - width + 1) if seen[tuple(w[i : i + width])] > 1 for p in range(i, i + width)}
        out.append((len(w), len(gone), hashlib.sha256(" ".join(x for i, x in enumerate(w) if i not in gone).encode()).hexdigest()))
    return out


@pytest.mark.parametrize("rule", [substrings.Runs(), substrings.Runs(segments=1), substrings.Runs(segments=2, longer=(10, 16, 27)), substrings.Runs(broadcast_rows=0)])
def test_repeated_runs(spark, rule):
    shared = prose(5, 50)
    texts = odd_texts() + [" ".join(prose(10 + k, k * 7) + shared[k % 3 : 40 + k] + prose(50 + k, 30)) for k in range(10)] + [" ".join(shared * 2)]
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substrings.remove_repeats(table(spark, texts), rule).collect()}
    assert [got[i] for i in range(len(texts))] == runs_by_force(texts, 35)


def test_repeated_runs_of_nothing(spark):
    assert substrings.remove_repeats(table(spark, ["a"]).limit(0)).count() == 0


def test_reference_spans(spark):
    ref = spark.createDataFrame([("a b c d e",), ("p q r s t u",), (None,)], "text string")
    docs = table(spark, ["x a b c d y", "q r s t z p", None, "a b c"])
    got = {r["doc_id"]: (r["n_removed"], r["kept_text"]) for r in substrings.remove_reference_spans(docs, ref, 4, shard_chars=8).collect()}
    assert got == {0: (4, "x y"), 1: (4, "z p"), 2: (0, ""), 3: (0, "a b c")}


def test_automaton_counts_occurrences():
    text = [1, 2, 1, 2, 1, 3, 1, 2, 1]
    tool = SuffixAutomaton()
    tool.add(text)
    tool.add([2, 1, 3], 2)
    tool.finish()
    assert tool.stream(text, 3, 3) == [3, 0, 1][:0] + [i for i in range(7) if sum(text[j : j + 3] == text[i : i + 3] for j in range(7)) + 2 * ([2, 1, 3] == text[i : i + 3]) >= 3]


def test_line_dedup(spark):
    assert compare(spark, QUERIES["op3_line_dedup"], ORACLE_SQL["op3_line_dedup"], "sf0.001") == ""
    texts = odd_texts()
    got = {r["doc_id"]: r for r in lines.dedup_lines(table(spark, texts)).collect()}
    assert got[11]["n_removed"] == 0 and got[12]["text"] == "x\ny" and got[13]["text"] == "" and got[0]["text"] is None and got[1]["text"] == ""
    left = lines.without_repeated_lines(table(spark, texts))
    assert left.columns == table(spark, texts).columns and left.where("doc_id = 13").count() == 0 and left.where("doc_id = 12").first()["n_chars"] == 3
    twice = table(spark, ["l1\nl2\nl3", "l1\nl2\nl3"], ids=[7, 7])
    assert [r["n_removed"] for r in lines.dedup_lines(twice).collect()] == [0, 0]
    assert lines.dedup_lines(table(spark, []).limit(0)).count() == 0


def shingles(text):
    w = [x.translate({i: i + 32 for i in range(65, 91)}) for x in WORD.findall(text or "")]
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())


def groups_by_force(texts, ids):
    sets = [shingles(t) for t in texts]
    root = list(range(len(texts)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(texts)):
        for j in range(i):
            common = len(sets[i] & sets[j])
            if common and 100 * common >= 75 * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b, key=lambda x: ids[x])] = min(a, b, key=lambda x: ids[x])
    return {ids[i]: ids[find(i)] for i in range(len(texts))}


@pytest.mark.parametrize("rule", [neardup.Forest(), neardup.Forest(reach=1, block_bytes=2000)])
def test_near_duplicates(spark, rule):
    r = random.Random(9)
    texts = odd_texts()
    base = prose(77, 120)
    for _ in range(14):  # copies with changes: some pairs link, some do not
        copy = list(base)
        for _ in range(r.randrange(1, 6)):
            copy[r.randrange(120)] = f"new{r.random()}"
        texts.append(" ".join(copy))
    ids = list(range(100, 100 + len(texts)))
    got = {x["doc_id"]: x for x in neardup.near_duplicates(table(spark, texts, ids=ids), rule).collect()}
    want = groups_by_force(texts, ids)
    assert {i: got[i]["component_id"] for i in ids} == want
    assert all(got[i]["kept"] == (want[i] == i) and got[i]["n_shingles"] == len(shingles(t)) for i, t in zip(ids, texts, strict=True))
    assert neardup.near_duplicates(table(spark, []).limit(0)).count() == 0


def test_tiling():
    import numpy as np

    doc, item = (np.array(x, np.uint64) for x in ([9, 5, 6, 7, 8, 9, 1, 2, 3, 4, 9], [1, 2, 3, 4, 5, 6, 7, 8]))
    assert sorted(tiles(doc, item, 3)) == [(1, 4, 4), (6, 0, 4)]
    assert tiles(doc, item[:2], 3) == []


def test_decontamination(spark):
    r = random.Random(4)
    item = prose(3, 30)
    cut = item[20:] + prose(8, 5) + item[10:20] + prose(9, 5) + item[:10]
    texts = [None, "", " ".join(item).upper(), " ".join(cut), " ".join(prose(6, 300)), " ".join(item[:6] + prose(7, 40)), " ".join(prose(r.random(), 9000) + item + prose(2, 10))]
    items = spark.createDataFrame([(5, " ".join(item)), (6, None), (7, ""), (8, " ".join(item))], "item_id long, text string")
    for size in (10_000_000, 50):
        got = {x["doc_id"]: x["item_id"] for x in contamination(table(spark, texts), items, Tiling(), block_chars=size).collect()}
        assert got == {0: None, 1: None, 2: 5, 3: 5, 4: None, 5: None, 6: 5}
    assert {x["item_id"] for x in contamination(table(spark, texts), items.limit(0)).collect()} == {None}


def test_language(spark):
    r = random.Random(0)
    kinds = {"aa": "bcdfgaeiou", "bb": "klmnpxyzaeo", "cc": "ßüöätrschei"}
    texts, langs = [], []
    for i in range(240):
        name = list(kinds)[i % 3]
        texts.append(" ".join("".join(r.choice(kinds[name]) for _ in range(r.randrange(2, 9))) for _ in range(60)))
        langs.append(name)
    texts += [None, "", "123 456 !", "x"]
    langs += [None, "aa", "bb", None]
    got = {x["doc_id"]: x for x in language.detect(table(spark, texts, langs)).collect()}
    held = [i for i in range(240) if got[i]["held_out"]]
    assert len(held) > 40 and all(got[i]["lang_pred"] == langs[i] for i in held)
    assert [got[i]["lang_pred"] for i in (240, 241, 242)] == ["und"] * 3 and all(0 <= x["score"] <= 1 for x in got.values())
    assert {x["lang_pred"] for x in language.detect(table(spark, ["abc"], [None])).collect()} == {"und"}
    assert language.detect(table(spark, []).limit(0)).count() == 0


def test_codec_equals_library(spark):
    from tokenizers import Tokenizer

    tool = Tokenizer.from_file(vocabulary(BYTE_BPE))
    texts = odd_texts() + ["I'll 'VE aaaaaaaa   \n\n  12½", "x" * 3000]
    got = {r["doc_id"]: r for r in encode_documents(table(spark, texts), vocabulary(BYTE_BPE), with_ids=True).collect()}
    for i, t in enumerate(texts):
        ids = tool.encode(t or "", add_special_tokens=False).ids
        assert got[i]["ids"] == ids and got[i]["n_tokens"] == len(ids) and got[i]["decoded"] == tool.decode(ids, skip_special_tokens=False)
        assert got[i]["ids_sha256"] == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()


def test_counts_equal_library(spark):
    from tokenizers import Tokenizer, models, pre_tokenizers

    pieces = read_pieces(vocabulary(PIECE_BPE))
    tool = Tokenizer(models.Unigram(pieces, 0, True))
    tool.pre_tokenizer = pre_tokenizers.Metaspace(prepend_scheme="always", split=True)
    texts = odd_texts() + ["  a  b ", "▁▁a b<0x41>"]
    got = {r["doc_id"]: r["n_tokens"] for r in count_tokens(table(spark, texts), vocabulary(PIECE_BPE)).collect()}
    assert [got[i] for i in range(len(texts))] == [len(tool.encode(t or "", add_special_tokens=False).ids) for t in texts]
    ties = BestPathCounter([("▁", -1.0), ("a", -1.0), ("▁a", -2.0), ("aa", -2.0)])
    assert ties.count("▁a") == 1 and ties.count("▁aa") == 2


def test_chat_round_trip(spark):
    assert compare(spark, QUERIES["op10_chat_examples"], ORACLE_SQL["op10_chat_examples"], "sf0.001") == ""
    rows = [(1, 0, "user", "a\\b #<\\l\\\\"), (1, 1, "assistant", " </turn>\n### assistant: "), (1, 2, "user", None), (2, 0, None, ""), (3, 0, "assistant", "x"), (3, 0, "assistant", "x"), (4, 0, "a:b", "t")]
    df = spark.createDataFrame(rows + PROBE, "conv_id long, turn long, role string, text string")
    made = format_examples(df)
    got = {r["conv_id"]: r for r in digest(made).collect()}
    assert got[1]["n_turns"] == 3 and got[1]["loss_chars"] == len(rows[1][3]) and got[3]["loss_chars"] == 2 and got[2]["loss_chars"] == 0
    want = hashlib.sha256("".join(f"{r or ''}\n{t or ''}\n" for c, _, r, t in rows if c == 1).encode()).hexdigest()
    assert got[1]["turns_sha256"] == want
    back = made.where("conv_id = 4").select(read_turns(F.col("formatted")).alias("t")).first()["t"]
    assert [(x["role"], x["text"]) for x in back] == [("a:b", "t")]
    assert digest(format_examples(df.limit(0))).count() == 0


PAGE = """<!DOCTYPE html><html><head><title>T</title><script>var a="</p>";</script></head><body class="x"><header><a href="/">Site {n}</a></header>
<nav><ul><li><a>one</a></li><li><a>two</a></li>{extra}</ul></nav><div class="cookie-notice">We use cookies</div><main><article><h1>Title {n} &amp; co</h1><p>First {n}  with <b>bold</b>
text<br>more &eacute;&#33;<p>Second {n}</p>{middle}<div class="share">Share this</div></article><section class="comments"><p>Reader {n} says a lot of things about everything and more</p></section></main><aside>Side {n}</aside>
<form><p>Mail</p></form><footer>&copy; {n}</footer>"""


def test_wrappers(spark):
    pages = [PAGE.format(n=i, extra="<li><a>three</a></li>" * (i % 3), middle=f"<ul><li>p{i}</li><li>q</li></ul>" * (i % 2)) for i in range(6)]
    assert container(infer(pages))[-1] == "article"
    want = [f"Title {i} & co\nFirst {i} with bold text more é!\nSecond {i}" + (f"\np{i}\nq" if i % 2 else "") for i in range(6)]
    assert [extract(p, [container(infer(pages))]) for p in pages] == want
    rows = [(i, f"http://h.example.com/{i}", p) for i, p in enumerate(pages)] + [(6, None, None), (7, "no url", ""), (8, "http://single.example.com", pages[0]), (8, "http://single.example.com", pages[0]), (9, "http://odd.example.com/", "<p>a < b<p>c</div><!-- x")]
    got = [(r["page_id"], r["text"], r["n_chars"]) for r in extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).orderBy("page_id").collect()]
    assert [t for _, t, _ in got] == [*want, "", "", want[0], want[0], "a < b\nc"] and all(len(t) == n for _, t, n in got)
    assert extract_pages(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_pages_of_the_table(spark):
    import html

    def plain(page):
        body = re.search(r"<article>(.*?)(</article>|\Z)", page, re.S).group(1)
        parts = (re.sub(r"\s+", " ", html.unescape(re.sub(r"<[^>]*>", "", x.replace("<br>", " ")))).strip() for x in re.split(r"</?(?:p|h1|article|div)[^>]*>", body))
        return "\n".join(p for p in parts if p)

    pages = {r["page_id"]: r["html"] for r in spark.read.parquet("/root/testdata/sf0.001/pages.parquet").collect()}
    got = {r["page_id"]: r["text"] for r in QUERIES["op9_host_wrappers"](spark, "/root/testdata/sf0.001").collect()}
    assert got == {i: plain(p) for i, p in pages.items()}


def test_wrappers_keep_sibling_blocks(spark):
    page = "<html><body><nav>Menu</nav><main><h1>T{n}</h1><section><h2>A{n}</h2><p>a{n}</p></section><section><h2>B{n}</h2><p>b{n}</p><ul><li>x{n}</li></ul><p>long {n} and longer</p></section></main></body></html>"
    pages = [page.format(n=i) for i in range(3)]
    want = [f"T{i}\nA{i}\na{i}\nB{i}\nb{i}\nx{i}\nlong {i} and longer" for i in range(3)]
    assert [extract(p, [container(infer(pages))]) for p in pages] == want
    assert [extract(p, []) for p in pages] == want
    part = "<div class='part'><h2>H{k}</h2>" + "".join(f"<{t}>{t}{{n}}</{t}>" for t in ("p", "pre", "blockquote", "h3", "h4", "h5")) + "</div>"
    pages = ["<html><body><h1>Title " + str(n) + "</h1><div class='all'>" + "".join(part.format(k=k, n=n) for k in range(4)) + "</div></body></html>" for n in range(3)]
    for p in pages:
        assert extract(p, [container(infer(pages))]).count("\n") == 28
    two = "<html><body><main><article><p>one {n}</p></article><article><p>two {n} is longer by far</p><ul><li>y</li></ul></article></main></body></html>"
    pages = [two.format(n=n) for n in range(3)]
    assert [extract(p, [container(infer(pages))]) for p in pages] == [f"one {n}\ntwo {n} is longer by far\ny" for n in range(3)]


def test_wrappers_of_rare_templates(spark):
    common = "<html><body><div class='top'>The same long words of the host stand on every single page</div><div class='body'><h1>T{n}</h1><p>text {n}</p></div></body></html>"
    rare = "<html><body><div class='top'>The same long words of the host stand on every single page</div><div class='story'><h1>R{n}</h1><p>rare {n}</p></div></body></html>"
    rows = [(n, f"http://h.example.com/{n}", (rare if n % 150 == 7 else common).format(n=n)) for n in range(450)]
    for limit in (10**6, 0):
        got = {r["page_id"]: r["text"] for r in extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string"), broadcast_bytes=limit).collect()}
        assert got == {n: f"R{n}\nrare {n}" if n % 150 == 7 else f"T{n}\ntext {n}" for n in range(450)}


def test_wrappers_drop_only_marked_parts(spark):
    page = """<html><body><nav>Menu</nav><article><h1>T{n}</h1><svg width="1"/><h2 id="related-work">Related work</h2><p>a{n}</p><math/><section id="search-algorithms"><p>b{n}</p></section>
<section id="recommended-dosage" class="notice-board"><p>c{n}</p></section><div class="share-buttons">Share this</div><div class="share">By mail</div><svg><text>drawn</text></svg><p>end {n}</p></article></body></html>"""
    rows = [(n, f"http://h.example.com/{n}", page.format(n=n)) for n in range(4)]
    got = {r["page_id"]: r["text"] for r in extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {n: f"T{n}\nRelated work\na{n}\nb{n}\nc{n}\nend {n}" for n in range(4)}


def test_items_without_an_id_contaminate(spark):
    words = prose(5, 40)
    docs = table(spark, [" ".join(words), " ".join(prose(6, 40)), None])
    items = spark.createDataFrame([(None, " ".join(words[5:30])), (3, "other words that match nothing at all here"), (None, None)], "item_id long, text string")
    for size in (10**6, 20):
        got = {r["doc_id"]: (r["item_id"], r["coverage"], r["longest_tile"]) for r in contamination(docs, items, block_chars=size).collect()}
        assert got == {0: (None, 1.0, 25), 1: (None, None, None), 2: (None, None, None)}


def test_near_duplicates_of_the_table(spark):
    rows = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text").collect()
    want = groups_by_force([r["text"] for r in rows], [r["doc_id"] for r in rows])
    got = {r["doc_id"]: r["component_id"] for r in QUERIES["op8_lsh_forest"](spark, "/root/testdata/sf0.01").collect()}
    assert got == want


@pytest.mark.parametrize("block_bytes", [8_000_000, 4000])
def test_crowded_regions(spark, block_bytes):
    """Hundreds of near copies of one text, many of them beyond the threshold from all others, beside exact copies."""
    r = random.Random(2)
    base, texts = prose(78, 100, 10**6), []
    for k in range(260):
        copy = list(base)
        for _ in range(r.choice((0, 1, 2, 3, 4, 5, 8))):
            copy[r.randrange(100)] = f"new{k}x{r.random()}"
        texts.append(" ".join(copy))
    got = {x["doc_id"]: x["component_id"] for x in neardup.near_duplicates(table(spark, texts), neardup.Forest(block_bytes=block_bytes)).collect()}
    want = groups_by_force(texts, list(range(260)))
    assert got == want and 20 < len(set(want.values())) < 250


def test_near_duplicates_of_odd_ids(spark):
    text = " ".join(prose(12, 60))
    rows = [(None, text), (None, None), (7, text), (7, " ".join(prose(13, 60))), (3, text), (7, text)]
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), with_key=True)
    seen = sorted(((r["doc_id"], r["component_id"], r["kept"]) for r in got.collect()), key=str)
    assert seen == sorted([(None, None, True), (None, None, True), (7, 3, False), (7, 7, True), (3, 3, True), (7, 3, False)], key=str)
    with pytest.raises(TypeError):
        neardup.near_duplicates(spark.createDataFrame([("a", text)], "doc_id string, text string"))


def test_repeated_runs_of_odd_rows(spark):
    shared = " ".join(prose(5, 50))
    rows = [("a", shared), ("a", shared), (None, shared + " x"), ("b", None)] + [("c", shared)] * 20
    got = substrings.remove_repeats(spark.createDataFrame(rows, "doc_id string, text string")).collect()
    assert sorted(str((r["doc_id"], r["n_words"], r["n_removed"])) for r in got) == sorted(str((i, len((t or "").split()), 50 if t else 0)) for i, t in rows)


def test_numerals_are_no_letters(spark):
    texts, langs = ["½ ² Ⅷ", "²", "abc def ghi " * 20, "где ты был " * 20, "日本語 文字 漢字 " * 20], [None, None, "en", "ru", "ja"]
    table_ = table(spark, texts * 3, langs * 3)
    profiles = language.fit(table_, F.lit(True))
    got = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language.predict(table_, profiles).collect()}
    assert [got[i][0] for i in range(5)] == ["und", "und", "en", "ru", "ja"] and got[0][1] == 0


def plain_places(text, size):
    words = "".join(c if c.isalpha() else " " for c in text.lower()).split()
    seen = Counter(g for w in words for n in (1, 2, 3) for i in range(len(w) + 3 - n) if (g := f" {w} "[i : i + n]) != " ")
    return sorted(seen, key=lambda g: (-seen[g], language.packed(g)))[:size]


def test_distances_equal_plain_ones():
    texts = ["the cat and the dog ½ sat on the mat", "le chat et le chien sont là", "Ünïted çités ß", "日本 の 語", "a b c d"]
    for size in (5, 30, 400):
        profiles = language.Profiles([str(i) for i in range(3)], [[language.packed(g) for g in plain_places(t, size)] for t in texts[:3]], size)
        for text in texts:
            mine, far = plain_places(text, size), []
            for t in texts[:3]:
                theirs = plain_places(t, size)
                far.append(sum(min(size, abs(theirs.index(g) - i)) if g in theirs else size for i, g in enumerate(mine)))
            assert language.distances(language.most_frequent(*language.grams(language.symbols(text)), size), profiles.prepared(), size).tolist() == far
            names, scores = language.classify([text], profiles, profiles.prepared())
            assert names == [str(far.index(min(far)))] and abs(scores[0] - (1 - min(far) / len(mine) / size)) < 1e-12


def test_language_of_the_table(spark):
    truth = {r["doc_id"]: r["lang"] for r in spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang").collect()}
    got = [r for r in QUERIES["op5_language_profiles"](spark, "/root/testdata/sf0.01").collect() if r["held_out"] and truth[r["doc_id"]] and r["lang_pred"] != "und"]
    assert len(got) > 250 and sum(r["lang_pred"] == truth[r["doc_id"]] for r in got) >= 0.99 * len(got)


def plain_tiles(doc, item, least):
    """Greedy tiling by definition: always the longest free match, the first in the item and then in the document."""
    free = [[True] * len(doc), [True] * len(item)]
    out = []
    while True:
        best = (0, 0, 0)
        for i in range(len(item)):
            for j in range(len(doc)):
                n = 0
                while i + n < len(item) and j + n < len(doc) and item[i + n] == doc[j + n] and free[0][j + n] and free[1][i + n]:
                    n += 1
                if n > best[0]:
                    best = (n, i, j)
        n, i, j = best
        if n < least:
            return sorted(out)
        free[0][j : j + n], free[1][i : i + n] = [False] * n, [False] * n
        out.append((j, i, n))


def test_tiling_equals_plain_tiling():
    import numpy as np

    from localcoef.llm.decontam import _stretches

    r = random.Random(5)
    for _ in range(1500):
        size, least = r.choice((2, 3, 8)), r.choice((2, 3))
        item, doc = (np.array([r.randrange(size) for _ in range(r.randrange(1, n))], np.uint64) for n in (14, 26))
        want = plain_tiles(doc.tolist(), item.tolist(), least)
        assert sorted(tiles(doc, item, least)) == want
        assert sorted(n for _, _, n in tiles(_stretches(doc, item, least), item, least)) == sorted(n for _, _, n in want)


def test_decontamination_of_the_table(spark):
    """All pairs of documents and items with plain tiling of what they share."""
    import numpy as np

    from localcoef.llm.textcore import WordBlock

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").collect()
    items = spark.read.parquet("/root/testdata/sf0.001/benchmark.parquet").select("item_id", "text").collect()
    block = WordBlock([r["text"] for r in items] + [r["text"] for r in docs], lower=True)
    words = [block.hashes()[a:b] for a, b in zip(block.first[:-1], block.first[1:], strict=True)]
    want = {}
    for d, w in zip(docs, words[len(items) :], strict=True):
        found = []
        for t, x in zip(items, words, strict=False):
            near = np.flatnonzero(np.isin(w, x))
            if len(x) and len(near) >= min(13, 0.5 * len(x)):
                got = plain_tiles(w[max(0, near[0] - 1) : near[-1] + 2].tolist(), x.tolist(), min(4, len(x)))
                share, longest = sum(n for *_, n in got) / len(x), max((n for *_, n in got), default=0)
                if share >= 0.5 or longest >= 13:
                    found.append((-share, t["item_id"], longest))
        want[d["doc_id"]] = (min(found)[1], -min(found)[0], min(found)[2]) if found else (None, None, None)
    got = {r["doc_id"]: (r["item_id"], r["coverage"], r["longest_tile"]) for r in QUERIES["op4_string_tiling"](spark, "/root/testdata/sf0.001").collect()}
    assert got == want and any(c for _, c, _ in want.values())


def test_hot_seeds(spark):
    from time import monotonic

    phrase = "one two three four five six"
    items = spark.createDataFrame([(f"i{k}", f"{phrase} x{k} y{k} z{k} w{k}") for k in range(300)] + [("none", None)], "item_id string, text string")
    began = monotonic()
    got = contamination(table(spark, [" ".join([phrase] * 300), "one two three"]), items).orderBy("doc_id").collect()
    assert [(r["item_id"], r["coverage"]) for r in got] == [("i0", 0.6), (None, None)] and monotonic() - began < 60


def test_repetition_verdict(spark):
    rules_limit = {"long": 6, "covered": 0.3, "longest": 0.2}
    r = random.Random(3)
    texts = ["\n".join(" ".join(r.choice("abcdefghijklmnopq") * r.randrange(1, 4) + r.choice(["", "#", "$|"]) for _ in range(r.randrange(1, 12))) for _ in range(r.randrange(1, 30))) for _ in range(60)]
    texts += [t + "\n" + t[: len(t) // 3] for t in texts] + [None, ""]
    got = {x["doc_id"]: x for x in score_quality(table(spark, texts)).collect()}
    for i, t in enumerate(texts):
        w = WORD.findall(t or "")
        best = [max((next((n for n in range(min(len(w) - a, len(w) - b) + 1) if a + n >= len(w) or b + n >= len(w) or w[a + n] != w[b + n]), 0) for b in range(len(w)) if b != a), default=0) for a in range(len(w))]
        covered = {p for a, n in enumerate(best) if n >= rules_limit["long"] for p in range(a, a + n)}
        lines_ = [x for x in (t or "").split("\n") if WORD.search(x)]
        assert got[i]["longest_repeat"] == max(best, default=0) and got[i]["n_long_repeat_words"] == len(covered)
        assert got[i]["n_symbols"] == len(re.findall(r"[#*$%&|<>]", t or "")) and got[i]["n_dup_lines"] == len(lines_) - len(set(lines_))
        verdict = len(covered) <= 0.3 * len(w) and max(best, default=0) <= max(0.2 * len(w), 6)
        assert got[i]["kept"] == (verdict and not got[i]["base_failed"])


def test_wrappers_of_deep_pages(spark):
    deep = "<html><body>" + "<div>" * 2500 + "x" + "<b>" * 2500 + "y<p>z" + "</div>" * 10
    rows = [(n, "http://h.example.com/", deep) for n in range(2)] + [(2, "http://h.example.com/", "<p>" * 3000 + "<ul><li>" * 1500)]
    got = {r["page_id"]: r["text"] for r in extract_pages(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {0: "xy\nz", 1: "xy\nz", 2: ""}


def test_alignment_is_longest():
    from localcoef.llm import wrappers

    r = random.Random(1)
    for bits in (1 << 28, 6, 40):
        for _ in range(200):
            a, b = ([r.randrange(4) for _ in range(r.randrange(14))] for _ in range(2))
            wrappers.ALIGN_BITS, pairs = bits, None
            pairs = wrappers.common(a, b)
            row = [0] * (len(b) + 1)
            for x in a:
                new = [0]
                for j, y in enumerate(b):
                    new.append(row[j] + 1 if x == y else max(new[-1], row[j + 1]))
                row = new
            assert len(pairs) == row[-1] and all(a[x] == b[y] for x, y in pairs) and all(p[0] < q[0] and p[1] < q[1] for p, q in zip(pairs, pairs[1:], strict=False))
    wrappers.ALIGN_BITS = 1 << 28
