"""Each operator on small fixtures, against brute force, a round trip, or known answers."""

import functools
import hashlib
import html
import math
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from netan.llm import decontamination, html_text, language_id, mixing, ngram_join, quality, sharding, substring_dedup, token_counts, token_files

ODD = [(1, None), (2, ""), (3, " \n\t "), (None, "a b c"), (None, "a b c"), (4, "x" * 50_000), (5, "a " * 3000), (5, "ü ß 日本 <|endoftext|> don't")]


def frame(spark, rows, extra=False):
    df = spark.createDataFrame(rows, "doc_id long, text string")
    return clashing(df) if extra else df


def clashing(df):
    """With columns whose names the operators use themselves."""
    names = ("rid", "n_words", "sid", "component", "n", "vec", "key", "budget", "epochs", "rest", "bits", "h", "range", "edge", "copies", "domain", "score", "kept", "held_out", "_gone_id", "_id", "_doc_id")
    return df.withColumns({c: F.lit("x") for c in names if c not in df.columns})


def rows_of(df):
    return sorted(map(tuple, df.collect()), key=repr)


def sha(words):
    return hashlib.sha256(" ".join(words).encode()).hexdigest()


# --- 1 mixing


def mixed_docs(spark):
    rows = [(k, "w " * (1 + k % 7), "en" if k % 3 else None, f"src{k % 4}") for k in range(400)] + [(1000, None, "en", None), (1001, "", "de", "src1"), (7, "w w", "en", "src1"), (7, "w w", "en", "src1")]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")


def test_mixing_fills_the_budget(spark):
    domain = F.when(F.col("source") == "src0", "a").otherwise("b")
    weight = F.when(F.col("source").isNotNull(), 1).when(F.col("lang").isNotNull(), 1).otherwise(F.when(F.col("domain") == "a", 3).otherwise(1))
    docs = mixed_docs(spark)
    total = docs.agg(F.sum(mixing.words(F.col("text")))).first()[0]
    out = mixing.mix(docs, domain, weight, 0.5, 4, 3)
    used = {r[0]: r[1] for r in out.groupBy("domain").agg(F.sum(F.col("copies") * F.col("n_tokens"))).collect()}
    assert used["a"] / used["b"] == pytest.approx(3, rel=0.2)  # a has a quarter of the tokens and is used in several epochs
    assert 0.9 * total / 2 < sum(used.values()) <= total / 2
    assert out.agg(F.max("copies")).first()[0] <= 4 and rows_of(out) == rows_of(mixing.mix(docs, domain, weight, 0.5, 4, 3))


def test_shortage_goes_to_siblings_first(spark):
    nodes = [("a", "x", "s1", 10, 1), ("a", "x", "s2", 1000, 1), ("a", "y", "s3", 1000, 1), ("b", "x", "s4", 5000, 1)]
    leaves = spark.createDataFrame([(d, l, s, t, r) for d, l, s, t, r in nodes], "domain string, lang string, source string, tokens long, rows long")
    got = {r.source: r.budget for r in mixing.budgets(leaves, F.lit(1), F.lit(800.0), 1).collect()}
    assert got == {"s1": 10, "s2": 190, "s3": 200, "s4": 400}


def test_mixing_of_an_empty_table(spark):
    docs = mixed_docs(spark).limit(0)
    assert rows_of(mixing.mix(docs, F.lit("d"), F.lit(1))) == []


def test_mixing_in_several_levels(spark, monkeypatch):
    """Ranges of two rows, found by two bits at first, choose the same documents as one order over each leaf."""
    docs = mixed_docs(spark).unionByName(spark.createDataFrame([(2000, "w " * 40_000, "en", "src1")], "doc_id long, text string, lang string, source string"))
    run = lambda d: rows_of(mixing.mix(d, F.lit("d"), F.lit(1), 0.4, 3, 5))
    want = run(docs)
    assert run(clashing(docs)) == want and len(want) > 50
    monkeypatch.setattr(mixing, "RANGE_ROWS", 2)
    monkeypatch.setattr(mixing, "LEVEL_BITS", 2)
    assert run(docs) == want


# --- 2 substring dedup


def brute_windows(docs, length):
    split = [(i, (t or "").encode().split()) for i, t in docs]
    seen = Counter(tuple(w[a : a + length]) for _, w in split for a in range(len(w) - length + 1))
    out = []
    for i, w in split:
        gone = {j for a in range(len(w) - length + 1) if seen[tuple(w[a : a + length])] > 1 for j in range(a, a + length)}
        kept = [x.decode() for j, x in enumerate(w) if j not in gone]
        out.append((i, len(w), len(gone), sha(kept)))
    return sorted(out, key=repr)


@pytest.mark.parametrize("most", [1000, 1])
def test_substring_dedup_against_brute_force(spark, monkeypatch, most):
    monkeypatch.setattr(substring_dedup, "SHARD_CONTENTS", most)
    rng = random.Random(3)
    shared = [rng.choice("abcdefgh") for _ in range(60)]
    docs = []
    for k in range(40):
        words = [rng.choice("abcdefghijklmnop") + rng.choice("xyz") for _ in range(rng.randint(0, 90))]
        if k % 3 == 0:
            a = rng.randint(0, 20)
            words[10:10] = shared[a : a + rng.randint(30, 40)]
        docs.append((k, " ".join(words)))
    docs += [(50, "q r " * 60), (51, docs[1][1]), *ODD]
    for length in (12, 35):
        assert rows_of(substring_dedup.remove(frame(spark, docs, True), length)) == brute_windows(docs, length)


def test_windows_of_one_text_in_pieces(monkeypatch):
    """Every window has the same anchor, at the same place, whether a text is sought through at once or in pieces."""
    words = np.random.default_rng(3).integers(0, 50, 400).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)

    def windows():
        found = substring_dedup.segments(words, np.array([len(words)]), 20)
        rows = zip(*(found[c].tolist() for c in ("start", "count", "off", "anchor")))
        return [(start + j, start + off, anchor) for start, count, off, anchor in rows for j in range(count)]

    whole = windows()
    monkeypatch.setattr(substring_dedup, "PIECE_WINDOWS", 50)
    assert windows() == whole and len(whole) == 381


def test_removed_spans_and_text(spark):
    same = " ".join(f"s{k}" for k in range(35))
    out = substring_dedup.remove(frame(spark, [(1, "a b " + same + " c"), (2, same + " d")]), with_text=True)
    got = {r.doc_id: (r.kept_text, [tuple(x) for x in r.removed]) for r in out.collect()}
    assert got == {1: ("a b c", [(2, 37)]), 2: ("d", [(0, 35)])}


def test_ngram_join_takes_texts_and_vectors_in_small_lots(monkeypatch):
    texts = ["é" * 30, None, "", "a" * 500, "b", "c" * 70]
    monkeypatch.setattr(ngram_join, "TEXT_CHARS", 100)
    column = pa.array(["x", *texts]).slice(1)
    got = [(t, b - a) for t, a, b in ngram_join._pieces(column)]
    assert [x for t, _ in got for x in t] == texts and len(got) > 1 and all(len(t) == n for t, n in got)
    points = np.random.default_rng(2).integers(0, 3, (40, ngram_join.GROUPS)).astype("<u4")
    held = pa.array([p.tobytes() for p in points], pa.binary())
    i, j = np.arange(39), np.arange(1, 40)
    want = ngram_join._close(points.astype(np.int32), points.astype(np.int32), i, j, 40)
    monkeypatch.setattr(ngram_join, "COMPARED", 7)
    assert (ngram_join._points(held.slice(3)) == points[3:]).all() and ngram_join._points(held.slice(40)).shape == (0, ngram_join.GROUPS)
    assert want.any() and (ngram_join._close(points.astype(np.int32), points.astype(np.int32), i, j, 40) == want).all()


def test_substring_dedup_lots_of_windows():
    """Equal windows at the same place about an anchor lie in lots of one core, and there are a quarter as many lots."""
    rng = np.random.default_rng(3)
    passage = rng.integers(0, 1 << 60, 50).astype(np.uint64)
    held, number = {}, [0, 0]
    for _ in range(30):
        words = np.concatenate((rng.integers(0, 1 << 60, rng.integers(0, 20)).astype(np.uint64), passage, rng.integers(0, 1 << 60, 20).astype(np.uint64)))
        found = substring_dedup.segments(words, np.array([len(words)]), 35)
        for start, count, anchor in zip(*(found[c].tolist() for c in ("start", "count", "anchor"))):
            got = substring_dedup.lots(words[start : start + count + 34], anchor, 35)
            places = sorted(lot["first"] - k for lot in got for k, w in enumerate(lot["windows"]) if w is not None)
            assert places == list(range(count)) and len(got) <= count // 4 + 2
            number[0] += len(got)
            number[1] += count
            for lot in got:
                for k, w in enumerate(lot["windows"]):
                    if w is not None:
                        assert held.setdefault((anchor, w), (lot["core"], k)) == (lot["core"], k)
    assert 2 * number[0] < number[1]


def test_suffix_automaton_counts_places():
    texts, rng = [], random.Random(1)
    for _ in range(12):
        texts.append([rng.randint(0, 2) for _ in range(rng.randint(1, 30))])
    automaton = substring_dedup.SuffixAutomaton()
    for t in texts:
        automaton.add(t)
    automaton.close()
    for t in texts:
        for k, (n, places) in enumerate(automaton.statistics(t, 4)):
            part = t[k - n + 1 : k + 1]
            assert n == min(4, k + 1) and places == sum(x[a : a + n] == part for x in texts for a in range(len(x) - n + 1))


# --- 3 html


PAGE = '<html><head><title>T</title><script>var a="<p>x</p>";</script></head><body><nav><ul><li><a href="/a">Home</a></li></ul></nav><div class="ad">Buy this now please</div><article><h1>Head &amp; tail</h1><p>One  two<br>three</p><!-- no --><p><b>Bold</b> word&nbsp;here</p><aside>Related things</aside></article><div id="comments"><p>First! I think so too</p></div><footer>&copy; someone in the world</footer></body></html>'


def test_html(spark):
    weights = html_text.learn([PAGE])
    assert html_text.extract(PAGE, weights) == "Head & tail\n\nOne two three\n\nBold word here"
    assert html_text.extract(None, weights) == html_text.extract("", weights) == html_text.extract("<p></p><!-- x", weights) == ""
    assert html_text.extract("<p>a<p>b &lt;c&gt;", weights) == "a\n\nb <c>"
    pages = spark.createDataFrame([(1, "u", PAGE), (2, None, None), (2, None, None), (None, "v", "plain")], "page_id long, url string, html string")
    got = rows_of(html_text.main_text(pages))
    assert [(r[0], r[3]) for r in got] == [(1, 42), (2, 0), (2, 0), (None, 5)]
    assert rows_of(html_text.main_text(pages.limit(0))) == []


BODY = "<h1>The title</h1><p>One two three four five six seven</p><p>end</p>"
TEXT = "The title\n\nOne two three four five six seven\n\nend"
LONG = "<p>" + "word " * 90 + "</p>"


@pytest.mark.parametrize(
    "page, want",
    [
        (f'<body><div class="layout has-sidebar">{BODY}</div></body>', TEXT),
        (f'<body><div id="post-with-comments">{BODY}</div></body>', TEXT),
        (f'<body><div class="sidebar">{BODY}</div></body>', TEXT),
        (f'<body><div data-class="ad">{BODY}</div></body>', TEXT),
        (f'<body><div title="x class=ad">{BODY}</div></body>', TEXT),
        (f"<body><header><h1>The site</h1>of some people</header><div>{BODY}</div></body>", TEXT),
        (f'<body><div class="masthead">Our site of old</div><div>{BODY}</div></body>', TEXT),
        ('<body><article><div class="entry-header"><h1>My title</h1></div><p>one two three four</p></article></body>', "My title\n\none two three four"),
        ("<body><article><header><h1>My title</h1></header><p>one two three four</p><footer>shared by many</footer></article></body>", "My title\n\none two three four"),
        ("<table><tr><td>a</td><td>b</td></tr></table>", "a\n\nb"),
        (f"<form><nav>Menu of the site</nav><div>{BODY}</div></form>", TEXT),
        (f'<body><div class="content">{BODY}</div><div class="comments">{LONG}</div></body>', TEXT),
        (f'<body><div class="content">{BODY}</div><section id="siteComments">{LONG}</section></body>', TEXT),
        (f"<body><ul><li><a>Home</a></li><li><a>About us</a></li></ul>{BODY}<ul><li>x</li><li>y</li></ul></body>", TEXT + "\n\nx\n\ny"),
        (f'<body><div class="cookie-notice">We use some of them</div><main>{BODY}<div class="ads">Buy now</div></main><form>Your name</form></body>', TEXT),
    ],
)
def test_pages_of_many_kinds(page, want):
    assert html_text.extract(page, {}) == want
    assert html_text.extract(page, html_text.learn([PAGE])) == want


def test_html_against_generated_pages(spark):
    """Pages put together from known parts: what is asked for is what was put in."""
    rng = random.Random(12)
    words = lambda a, b: " ".join(rng.choice(["sol", "luna", "mar &amp; cielo", "x", "5 &lt; 6", "r&eacute;el", "fin."]) for _ in range(rng.randint(a, b)))
    noise = [
        lambda: f"<nav><ul><li><a href=/>{words(1, 3)}</a></li></ul></nav>", lambda: f"<aside><p>{words(1, 30)}</p></aside>", lambda: f'<div class="ad">{words(1, 20)}</div>', lambda: f"<header><p>{words(1, 6)}</p></header>",
        lambda: f"<footer>&copy; {words(1, 20)}</footer>", lambda: f"<form><p>{words(1, 5)}</p><button>go</button></form>", lambda: f'<div id="comments"><p>{words(1, 60)}</p><p>{words(1, 40)}</p></div>', lambda: "<script>if (a < b) c('<p>no</p>')</script>", lambda: f"<!-- {words(1, 4)} -->",
    ]
    pages = []
    for k in range(60):
        blocks = [words(3, 40) for _ in range(rng.randint(1, 6))]
        body = "".join(f"<p>{b}</p>" if j else f"<h1>{b}</h1>" for j, b in enumerate(blocks))
        inside = ("<article>%s</article>", "<main>%s</main>", '<div class="post">%s</div>', "<div class='wrap'><div>%s</div></div>")[k % 4] % body
        around = lambda: "".join(rng.choice(noise)() for _ in range(rng.randint(0, 4)))
        page = f"<html><head><title>t</title></head><body>{around()}{inside}{around()}</body></html>"
        pages.append((k, page, "\n\n".join(html.unescape(" ".join(b.split())) for b in blocks)))
    df = spark.createDataFrame([(k, "u", p) for k, p, _ in pages] + [(99, "u", "<p>" + "long " * 60_000)], "page_id long, url string, html string")
    got = {r.page_id: r for r in html_text.main_text(clashing(df)).collect()}
    for k, page, want in pages:
        assert got[k].text == want, page
        assert got[k].n_chars == len(want)
    assert got[99].n_chars == 5 * 60_000 - 1


def test_sample_of_labelled_pages(spark):
    pages = spark.range(2000).select(F.col("id").alias("page_id"), F.concat(F.lit("<article>"), F.col("id").cast("string")).alias("html"))
    assert 50 < len(html_text.labelled_sample(pages, 100)) < 150
    assert len(html_text.labelled_sample(pages, 5000)) == 2000


def test_best_stretch_is_the_maximum():
    rng, weights = random.Random(2), {"o:p": -1.5, "c:p": -0.5}
    for _ in range(200):
        found = [("t", "", rng.randint(0, 4)) if rng.random() < 0.5 else (rng.choice("oc"), "p", 0) for _ in range(12)]
        score = lambda a, b: sum(x[2] if x[0] == "t" else weights[html_text.key(x)] for x in found[a:b])
        a, b = html_text.best(found, weights)
        assert score(a, b) == pytest.approx(max(0, max(score(x, y) for x in range(12) for y in range(x, 13))))


# --- 4 language id


def test_forward_sums_all_segmentations():
    pieces = language_id.Pieces("piece_bpe_32k.model")
    rng = np.random.default_rng(1)
    p = rng.random(len(pieces)) / 100
    tool = token_counts.library("piece_bpe_32k.model")
    names = [tool.id_to_piece(k) for k in range(tool.get_piece_size()) if not (tool.is_control(k) or tool.is_unknown(k) or tool.is_byte(k))]
    assert len(pieces) == len(names) + 1
    number = {x: k for k, x in enumerate(names)}
    for word in ("▁the", "▁q日x", "▁", "▁" + "straßenbahnhaltestelle"):

        @functools.cache
        def brute(a, word=word):
            if a == len(word):
                return 1.0
            parts = {b: number.get(word[a:b], pieces.other if b == a + 1 else -1) for b in range(a + 1, len(word) + 1)}
            return sum(p[k] * brute(b) for b, k in parts.items() if k >= 0)

        lattice = pieces.lattice([word])
        assert language_id.log_probability(lattice, p)[0] == pytest.approx(math.log(brute(0)))
        tiny = language_id.log_probability(lattice, p * 1e-40)  # by way of logarithms
        cuts = language_id.log_probability(lattice, np.ones(len(pieces)))
        assert cuts[0] == pytest.approx(math.log(sum_of_cuts(word, number)))
        assert tiny[0] < language_id.log_probability(lattice, p)[0] - 40
        counts = np.zeros(len(pieces))
        language_id.expected(lattice, p, np.array([2.0]), counts)
        assert sum(counts[k] * len(x) for x, k in number.items()) + counts[pieces.other] == pytest.approx(2 * len(word))


def sum_of_cuts(word, number):
    ways = [1] + [0] * len(word)
    for b in range(1, len(word) + 1):
        ways[b] = sum(ways[a] for a in range(b) if word[a:b] in number or b == a + 1)
    return ways[-1]


def test_long_words_do_not_tie(spark):
    """Probabilities as a very large corpus leaves them: a word's sum is below the least positive number."""
    pieces = language_id.Pieces("piece_bpe_32k.model")
    p = np.full((len(pieces), 2), [1e-15, 2e-15], np.float32)
    found = language_id.Scorer(pieces, p).score([["qzx" * 10], ["日" * 200]])
    assert np.isfinite(found).all() and (found[:, 1] > found[:, 0] + 5).all()
    docs = spark.createDataFrame([(k, "the house " * 3 + "日本" * 4000, "en") for k in range(4)] + [(9, "q" * 30_000, "de")], "doc_id long, text string, lang string")
    assert len(rows_of(language_id.identify(clashing(docs)))) == 5


def test_language_id(spark):
    text = {"en": "the house and the tree of this world are here with the other things", "de": "das Haus und der Baum sind hier mit den anderen Dingen dieser Welt", "fr": "la maison et les arbres de ce monde sont avec les autres choses"}
    rows = [(k, " ".join(random.Random(k).sample(text[lang].split(), 8)), lang) for k in range(120) for lang in [list(text)[k % 3]]]
    rows += [(200, None, "en"), (201, "12 !?", "en"), (202, "la maison des arbres", None), (202, "la maison des arbres", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = defaultdict(list)
    for r in language_id.identify(docs).collect():
        got[r.doc_id].append(r)
    assert all(r.lang_pred == rows[k][2] for k in range(120) for r in got[k])
    assert got[0][0].held_out == (zlib.crc32(b"0") % 4 == 2) and 0.34 < got[0][0].score <= 1
    assert [(r.lang_pred, r.score) for k in (200, 201) for r in got[k]] == [("und", 0.0)] * 2 and [r.lang_pred for r in got[202]] == ["fr"] * 2
    assert rows_of(language_id.identify(docs.limit(0))) == []
    assert {r.lang_pred for r in language_id.identify(docs.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}


def test_language_workers_take_in_bounded_batches_and_lots(spark, tmp_path, monkeypatch):
    """Of 30 MB of texts in one task, no worker holds more than a batch, and no more different words than it may count."""
    from netan.llm import common

    def watched(df, work, schema, keeps=False):
        def run(batches):
            def small():
                for b in batches:
                    assert b.nbytes < 2 * common.BATCH_BYTES, "a batch is too large"
                    yield b

            for columns in work(small()):
                assert len(columns.get("word", ())) <= 1000, "too many words at once"
                yield columns

        return common.arrow_map(df, run, schema, keeps)

    letters = "abcdefghijklmnopqrstuvwxyz"
    word = lambda n: "".join(letters[n // 26**k % 26] for k in range(3))
    rows = [(k, " ".join(map(word, range(k, k + 3000))) + " the" * 150_000, ("en", "de")[k % 2]) for k in range(50)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string").coalesce(1).write.parquet(str(tmp_path / "d"))
    docs = spark.read.parquet(str(tmp_path / "d")).coalesce(1)
    monkeypatch.setattr(language_id, "arrow_map", watched)
    monkeypatch.setattr(language_id, "COUNTED_WORDS", 500)
    monkeypatch.setattr(language_id, "LOT", 1000)
    with common.light_batches(spark):
        counts = {(r.lang, r.word): r.n for r in language_id.count_words(docs.select("text", "lang")).collect()}
    want = Counter((lang, "▁" + w) for _, text, lang in rows for w in text.split())
    assert counts == dict(want)
    assert len(rows_of(language_id.identify(docs))) == 50


# --- 5 decontamination


def test_a_single_block_is_judged_by_the_workers_that_find_its_spans(spark):
    docs = frame(spark, [(1, "a b c d e f g h i j k l m n o"), (2, "x y"), (3, None)], True)
    bench = spark.createDataFrame([("q", "b c d e f g h i j k l m n")], "item_id string, text string")
    judged = decontamination.judge(decontamination.build_index(docs), bench)
    assert judged._jdf.queryExecution().executedPlan().toString().count("MapInArrow") == 1
    assert rows_of(judged.select("doc_id", "n_words", "n_hit", "contaminated")) == [(1, 15, 13, True), (2, 2, 0, False), (3, 0, 0, False)]


def test_batches_for_workers_are_bounded_by_bytes(spark, tmp_path):
    from netan.llm.common import BATCH_BYTES, light_batches

    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name)
    text = "word " * 20_000
    spark.createDataFrame([(k, text) for k in range(300)], "doc_id long, text string").coalesce(1).write.parquet(str(tmp_path / "d"))
    docs = spark.read.parquet(str(tmp_path / "d")).coalesce(1)
    with light_batches(spark):
        found = [x.n for x in docs.mapInArrow(lambda batches: (pa.RecordBatch.from_pydict({"n": [b.nbytes]}) for b in batches), "n long").collect()]
    assert len(found) > 3 and max(found) < BATCH_BYTES + 2 * len(text) and spark.conf.get(name) == before


def test_decontamination_against_brute_force(spark, monkeypatch):
    rng = random.Random(4)
    word = lambda: rng.choice("abcdefgh") + rng.choice("xyz")
    items = [(k, " ".join(word() for _ in range(rng.choice([3, 13, 20])))) for k in range(12)] + [(90, None), (91, ""), (1, "ax bx Cx")]
    docs = []
    for k in range(60):
        words = [word() for _ in range(rng.randint(0, 80))]
        if k % 2:
            held = items[k % 12][1].upper().split()
            words[5:5] = held[: rng.randint(2, len(held))]
        docs.append((k, ", ".join(words)))
    docs += [*ODD, (70, docs[1][1])]
    windows = defaultdict(set)
    for i, t in items:
        w = [x.decode() for x in decontamination.terms(t)]
        for a in range(max(1, len(w) - 12) if w else 0):
            windows[tuple(w[a : a + 13])].add(str(i))
    want = []
    for i, t in docs:
        w, hit, found = [x.decode() for x in decontamination.terms(t)], set(), set()
        for x, names in windows.items():
            for a in range(len(w) - len(x) + 1):
                if tuple(w[a : a + len(x)]) == x:
                    hit.update(range(a, a + len(x)))
                    found |= names
        want.append((i, len(w), len(hit), len(found), hashlib.sha256(",".join(sorted(found)).encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)))
    index = decontamination.build_index(frame(spark, docs, True))
    bench = spark.createDataFrame(items, "item_id long, text string")
    columns = ["doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated"]
    assert rows_of(decontamination.judge(index, bench).select(*columns)) == sorted(want, key=repr)
    monkeypatch.setattr(decontamination, "BLOCK_CHARS", 100)  # several blocks of items
    assert rows_of(decontamination.judge(index, bench).select(*columns)) == sorted(want, key=repr)
    assert rows_of(decontamination.decontaminate(frame(spark, docs, True), bench).select(*columns)) == sorted(want, key=repr)
    assert rows_of(decontamination.judge(index, bench.limit(0)).where("n_hit > 0")) == []


def test_phrase_and_proximity(spark):
    index = decontamination.build_index(frame(spark, [(1, "a b c d"), (2, "c x a b"), (3, "a b")]))
    bench = spark.createDataFrame([(7, "A, b c")], "item_id long, text string")
    assert rows_of(decontamination.search(index, bench).drop("rid")) == [("7", 1, 0, 3)]
    assert rows_of(decontamination.search(index, bench, slop=1).drop("rid")) == [("7", 1, 0, 0), ("7", 2, 0, 0)]


# --- 6 quality


def brute_counts(text):
    import re

    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    seen = Counter(zip(words, words[1:], words[2:]))
    cover = {j for a in range(len(words) - 2) if seen[tuple(words[a : a + 3])] > 1 for j in range(a, a + 3)}
    dup = sum(x in lines[:k] for k, x in enumerate(lines))
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), dup, len(cover)


def test_quality(spark):
    rng = random.Random(6)
    clean = [" ".join("".join(rng.choice(["th", "an", "er", "on", "in"]) for _ in range(rng.randint(1, 4))) for _ in range(80)) for _ in range(60)]
    docs = [(1000 + k, t) for k, t in enumerate(clean)] + [(100, "\n".join(["zq#x kkq&& vvx$$ qqz"] * 1) + " " + " ".join(rng.choice("qxzkvw") * 3 + rng.choice("qxzkvw") + "&&&" for _ in range(90)))]
    docs += [(101, "a b c\na b c\n\n x\n x \na b c d a b c"), *ODD, (1000, clean[0])]
    got = quality.assess(frame(spark, docs, True).withColumn("lang", F.when(F.col("doc_id") == 3, None).otherwise("en"))).collect()
    want = sorted(((i, *brute_counts(t)) for i, t in docs), key=repr)
    assert sorted(((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in got), key=repr) == want
    kept = {r.doc_id: r.kept for r in got}
    assert all(kept[1000 + k] for k in range(60)) and not kept[100] and not kept[101] and not kept[1] and not kept[5]


def test_kneser_ney_sums_to_one(spark):
    docs = spark.createDataFrame([("the then than them", "en"), ("der die das", "de")], "text string, lang string")
    order, tables = quality.load(quality.train(docs))
    assert order == 4 and set(tables) == {"en", "de"}
    scorer = quality.Scorer(order, tables["en"])
    code, _ = quality.grams(*quality.folded(["the", "qx"]))
    for k in range(len(code)):  # in each context, seen or not
        every = (code[k] >> 16 << 16 | np.arange(1 << 16)).astype(np.int64)
        assert np.exp(scorer.log_probabilities(every)).sum() == pytest.approx(1, abs=1e-5)


def brute_kneser_ney(words):
    """log p of a symbol after three others, by dictionaries of tuples: modified Kneser-Ney with the counts of counts of each size."""
    top = Counter()
    for w, n in words.items():
        s = ["<", "<", "<", *w, ">"]
        for a in range(len(s) - 3):
            top[tuple(s[a : a + 4])] += n
    counts = {4: top}
    for size in (3, 2, 1):
        counts[size] = Counter(g[1:] for g in counts[size + 1])
    cuts = {}
    for size, c in counts.items():
        n = Counter(c.values())
        y = n[1] / (n[1] + 2 * n[2]) if n[1] else None
        cuts[size] = [min(k, max(0.05 * k, k - (k + 1) * y * n[k + 1] / n[k])) if y is not None and n[k] else 0.5 * k for k in (1, 2, 3)]
    total, spare = defaultdict(float), defaultdict(float)
    for size, c in counts.items():
        for g, n in c.items():
            total[g[:-1]] += n
            spare[g[:-1]] += min(n, cuts[size][min(n, 3) - 1])

    def p(gram):
        if not gram:
            return 1 / (1 << 16)
        low, context = p(gram[1:]), gram[:-1]
        if context not in total:
            return low
        n = counts[len(gram)][gram]
        return ((n - min(n, cuts[len(gram)][min(n, 3) - 1]) if n else 0) + spare[context] * low) / total[context]

    return lambda gram: math.log(p(tuple(gram)))


def test_model_against_another_kneser_ney(spark):
    texts = {"en": "the then than them these there theme thin thing the the of off often a an and at", "ja": "日本 日本語 本日 語学 学日 日日 本 語", "de": "straße strasse Straßen groß größe"}
    texts["xx"] = "aaaa " * 9
    docs = spark.createDataFrame([(t, lang) for lang, t in texts.items()], "text string, lang string")
    _, tables = quality.load(quality.train(docs))
    for lang, text in texts.items():
        other = brute_kneser_ney(Counter(w.lower() for w in text.split()))
        scorer = quality.Scorer(4, tables[lang])
        for word in {*text.split(), "tho", "日語", "zzz", "thé"}:
            s = ["<", "<", "<", *word.lower(), ">"]
            want = sum(other(s[a : a + 4]) for a in range(len(s) - 3))
            assert scorer._score([word])[0] == pytest.approx(want, rel=1e-5), (lang, word)


def test_scripts_keep_their_letters():
    symbols, first = quality.folded(["Ab3", "日本", "ж", "\U00020000x", "É"])
    assert symbols.tolist() == [0, 0, 0, 97, 98, 48, 1, 0, 0, 0, 0x65E5, 0x672C, 1, 0, 0, 0, 0x436, 1, 0, 0, 0, 0xD800 + 0x20000 % 2048, 120, 1, 0, 0, 0, 0xE9, 1]
    assert first.tolist() == [0, 7, 13, 18, 24]


def test_both_bands_reject(spark):
    """Texts of one very common word in many guises lie below the band, those of rare letters above."""
    rng = random.Random(21)
    syllables = ["th", "an", "er", "on", "in", "re", "st", "al", "lo", "mi", "qua", "fre", "spo", "bri"]
    word = lambda: "".join(rng.choice(syllables) for _ in range(rng.randint(2, 4)))
    common = [word() for _ in range(12)]
    docs = [(k, " ".join(rng.choice(common) if rng.random() < 0.5 else word() for _ in range(120))) for k in range(300)]
    docs += [(1000, " ".join(rng.choice(common) for _ in range(120))), (1001, " ".join(rng.choice("qxzkvw") * 2 + rng.choice("#%") for _ in range(120)))]
    got = {r.doc_id: r for r in quality.assess(frame(spark, docs, True).withColumn("lang", F.lit("en")), below=4.0).collect()}
    assert got[1000].score < got[1000].low and not got[1000].kept and got[1001].score > got[1001].high and not got[1001].kept
    assert sum(r.kept for r in got.values()) > 0.95 * 300


def test_moderate_junk_is_rejected_in_every_language(spark):
    """Junk at 8 deviations above and 11 below, in languages whose scores scatter differently."""
    rows = []
    for lang, scatter in (("en", 0.02), ("es", 0.04)):
        rows += [(k, lang, 1.8 + scatter * (k - 100) / 50, False) for k in range(201)]
        rows += [(1000, lang, 1.8 + 8 * scatter, False), (1001, lang, 1.8 - 11 * scatter, False), (1002, lang, 1.8 + 99, True)]
    bands = {r.lang: r for r in quality.bands(spark.createDataFrame(rows, "doc_id long, lang string, score double, base_failed boolean")).collect()}
    for _, lang, score, _ in (x for x in rows if x[0] < 1002):
        assert (bands[lang].low <= score <= bands[lang].high) == (abs(score - 1.8) < 0.1), (lang, score)


def test_quality_is_the_same_in_lots(spark, monkeypatch):
    rng = random.Random(16)
    docs = [(k, " ".join("".join(rng.choice(["th", "an", "er", "qu"]) for _ in range(rng.randint(1, 4))) for _ in range(60)), ["en", "de", "fr"][k % 3]) for k in range(30)]
    docs += [(100, None, "xx"), (101, "short", None), (0, docs[0][1], "en")]
    docs = spark.createDataFrame(docs, "doc_id long, text string, lang string")
    want = {r.doc_id: r for r in quality.assess(docs).collect()}
    monkeypatch.setattr(quality, "MOST_ROWS", 400)
    monkeypatch.setattr(quality, "FETCHED_ROWS", 100, raising=False)
    got = quality.assess(docs).collect()
    assert len(got) == docs.count()
    for r in got:
        assert r.score == (None if want[r.doc_id].score is None else pytest.approx(want[r.doc_id].score, abs=1e-9))
        assert r.kept == want[r.doc_id].kept and r.n_words == want[r.doc_id].n_words


# --- 7 token files


@pytest.mark.parametrize("high", [2, 1000, 49_408, 2**33, 2**62])
def test_blocks_round_trip(high):
    rng = np.random.default_rng(high % 97)
    for n in (0, 1, 59, 4095, 4096, 4097, 20_000):
        v = rng.integers(0, high, n).astype(np.uint64)
        assert (token_files.unpack(token_files.pack(v)) == v).all()
    mixed = np.where(np.arange(9000) % 997 == 0, np.uint64(2**63), np.uint64(5))
    assert (token_files.unpack(token_files.pack(mixed)) == mixed).all()


def test_token_files_against_the_library(spark):
    docs = ODD + [(k, f"Doc {k}, it's  a\x1cb \n x. END!!") for k in range(20, 60)]
    tool = token_counts.library("word_bpe_49k.json")
    order = sorted(docs, key=lambda d: (d[0] is not None, d[0] or 0, d[1] is not None, (d[1] or "").encode()))
    want, start = [], 0
    for i, t in order:
        ids = tool.encode(t or "", add_special_tokens=False).ids + [1]
        want.append((i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    for parts in (None, 3):
        got = token_files.read_ids(token_files.write_ids(frame(spark, docs, True).repartition(4), partitions=parts))
        assert rows_of(got) == sorted(want, key=repr)
    assert rows_of(token_files.read_ids(token_files.write_ids(frame(spark, docs).limit(0)))) == []


# --- 8 n-gram join


def brute_components(docs, size=4, per_cent=85):
    sets = []
    for _, t in docs:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[a : a + size]) for a in range(len(w) - size + 1)} if len(w) >= size else {tuple(w)} if w else set())
    label = list(range(len(docs)))
    for a in range(len(docs)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * both >= per_cent * (len(sets[a]) + len(sets[b]) - both):
                x, y = label[a], label[b]
                label = [min(x, y) if z in (x, y) else z for z in label]
    least = defaultdict(list)
    for (i, _), z in zip(docs, label):
        least[z].append(i)
    return sorted(((i, len(s), min((x for x in least[z] if x is not None), default=None)) for (i, _), s, z in zip(docs, sets, label)), key=repr)


@pytest.mark.parametrize("block, leaf, marks", [(4000, 32, True), (5, 2, True), (5, 2, False)])
def test_ngram_join_against_brute_force(spark, monkeypatch, block, leaf, marks):
    """Also with large groups cut in blocks, trees of small leaves, and nothing joined beforehand."""
    monkeypatch.setattr(ngram_join, "BLOCK", block)
    monkeypatch.setattr(ngram_join, "LEAF", leaf)
    if not marks:
        monkeypatch.setattr(ngram_join, "_first_links", lambda rows, *_: rows.sparkSession.createDataFrame([], "src long, dst long"))
    rng, docs = random.Random(7), []
    names = [f"w{k}" for k in range(500)]
    boiler = [rng.choice(names) for _ in range(30)]
    for _ in range(14):
        base = [rng.choice(names) for _ in range(rng.choice([2, 5, 30, 120, 300]))]
        for _ in range(rng.randint(1, 8)):
            w = list(base)
            for _ in range(rng.randint(0, max(1, len(w) // 40))):
                w[rng.randrange(len(w))] = rng.choice(names)
            docs.append((len(docs), " ".join(w)))
    docs += [(200 + k, " ".join([rng.choice(names) for _ in range(rng.randint(3, 40))] + boiler)) for k in range(40)]
    docs += ODD + [(300, docs[0][1].upper()), (7, "x"), (8, "X")]
    got = ngram_join.similar(frame(spark, docs, True).repartition(3)).select("doc_id", "n_shingles", "component_id")
    assert rows_of(got) == brute_components(docs)


def test_every_link_against_brute_force(spark, monkeypatch):
    """40 near copies with different texts, in groups that are split into blocks."""
    monkeypatch.setattr(ngram_join, "BLOCK", 6, raising=False)
    base = [f"w{k}" for k in range(200)]  # texts link if three words differ between them, not if four do
    docs = [(k, " ".join(f"x{k}-{j}" if j in [k + 4, k + 60, k + 120][: 1 + k % 3] else w for j, w in enumerate(base))) for k in range(40)]
    docs += [(50, docs[3][1]), (51, None), (52, "quite another text of six words")]
    sets = {i: {tuple(w[a : a + 4]) for a in range(len(w) - 3)} for i, t in docs if (w := (t or "").split())}
    texts = dict(docs)
    want = {i: len({texts[j] for j in sets if texts[j] != texts[i] and 100 * len(sets[i] & sets[j]) >= 85 * len(sets[i] | sets[j])}) if i in sets else 0 for i in texts}
    got = {r.doc_id: r.n_links for r in ngram_join.link_counts(frame(spark, docs, True).repartition(3)).collect()}
    assert got == want and sum(want.values()) > 100


def test_tree_finds_all_that_the_bound_allows():
    rng = np.random.default_rng(3)
    base = rng.poisson(6, (12, 32))
    points = np.vstack([np.maximum(0, b + rng.integers(-1, 2, (25, 32))) for b in base])
    tree = ngram_join.CountTree(points, leaf=8)
    for p in points[::9]:
        least = np.minimum(points, p).sum(axis=1)
        want = np.flatnonzero((185 * least >= 85 * (p.sum() + points.sum(axis=1))))
        assert set(want) <= set(tree.near(p, 85).tolist()) | set(np.flatnonzero(100 * np.minimum(points.sum(1), p.sum()) < 85 * np.maximum(points.sum(1), p.sum())))


def test_ngram_join_of_an_empty_table(spark):
    assert rows_of(ngram_join.similar(frame(spark, ODD).limit(0))) == []


# --- 9 sharding


def test_sharding(spark):
    shards = {"a": 1, "b": 1, "c": 2}
    table = sharding.fill(shards, 1009)
    count = Counter(table)
    assert count["c"] == pytest.approx(2 * count["a"], abs=3) and sum(count.values()) == 1009
    assert sharding.moved(shards, shards | {"d": 1}, 1009) < 0.35  # a fifth must move
    docs = frame(spark, ODD, True)
    got = sharding.place(docs, shards, 1009).collect()
    want = lambda i: table[int(hashlib.md5(("null" if i is None else str(i)).encode()).hexdigest()[:15], 16) % 1009]
    assert len(got) == len(ODD) and all(r.shard == want(r.doc_id) for r in got)
    assert rows_of(sharding.place(docs.limit(0), shards, 1009)) == []
    assert {r.shard for r in sharding.lookup_table(spark, {"a\tb": 1, 'c"d': 1}, 101).collect()} == {"a\tb", 'c"d'}
    with pytest.raises(ValueError):
        sharding.fill(shards, 1008)


# --- 10 token counts


def test_token_counts_against_the_library(spark):
    texts = ["a  b\n\nc", "x \ny", " \n ", "\n", "don't stop 's é̀ ́x y z  ", "it's\tTab", "\n a", "a\n", "a ", "a b\t", "a \tb", "a\t b c", "A\x85 b", "x.\nY, z!\nW", " lead", "a\x1cb c"]
    docs = ODD + [(10 + k, t) for k, t in enumerate(texts)]
    for name in ("byte_bpe_50k.json", "piece_bpe_32k.model"):
        tool = token_counts.library(name)
        size = (lambda t: len(tool.encode(t))) if name.endswith(".model") else (lambda t: len(tool.encode(t, add_special_tokens=False).ids))
        want = sorted(((i, len((t or "").encode()), size(t or ""), size(t or "") > 512) for i, t in docs), key=repr)
        assert rows_of(token_counts.count_tokens(frame(spark, docs, True), name)) == want
