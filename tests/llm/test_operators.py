import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict
from itertools import combinations

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from sparkspan.llm import bpe, exact_dedup, html_extract, line_dedup, mixing, quality_model, quality_rules, simhash, toxicity, warc
from sparkspan.llm.common import Written, vocabulary_path

WORD = re.compile(r"[^\x20\x09-\x0D]+")
FOLD = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SF = "/root/testdata/sf0.001"


def rows(df):
    return [r.asDict() for r in df.collect()]


def test_line_dedup_keeps_first_and_every_line(spark, odd, none):
    got = {r["doc_id"]: r for r in rows(line_dedup.dedup_lines(odd, Written(odd.sparkSession, "t")))}
    assert got[7]["text"] == "a\nb\nc\nd" and got[8]["text"] == "x\ny" and got[8]["n_removed"] == 3
    assert got[0]["text"] == "" and got[0]["n_removed"] == 0 and got[5]["n_lines"] == 1
    assert line_dedup.dedup_lines(none, Written(none.sparkSession, "t")).count() == 0
    docs = spark.createDataFrame([(i, "\n".join(random.Random(i).choice("abcd") for _ in range(12))) for i in range(60)], "doc_id bigint, text string")
    kept = {r["doc_id"]: r for r in rows(line_dedup.dedup_lines(docs, Written(spark, "t")))}
    seen, lines = set(), set()
    for i, t in sorted((r["doc_id"], r["text"]) for r in rows(docs)):
        ls, gone = t.split("\n"), set()
        for p in range(len(ls) - 2):
            w = tuple(ls[p : p + 3])
            gone |= {p, p + 1, p + 2} if w in seen else set()
            seen.add(w)
        assert kept[i]["text"] == "\n".join(x for p, x in enumerate(ls) if p not in gone)
        lines |= set(ls)
    assert lines == {x for r in kept.values() for x in r["text"].split("\n") if x}


def test_line_dedup_of_short_texts(spark):
    texts = ["a", "a", "a\nb", "a\nb", "b\na", "a\nb\nc", "x\na\nb\nc", None, "", " \n ", " \n "]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").repartition(3)
    got = [(r["text"], r["n_removed"]) for r in sorted(rows(line_dedup.dedup_lines(docs, Written(spark, "t"), short=True)), key=lambda r: r["doc_id"])]
    assert got == [("a", 0), ("", 1), ("a\nb", 0), ("", 2), ("b\na", 0), ("a\nb\nc", 0), ("x", 3), ("", 0), ("", 0), (" \n ", 0), (" \n ", 0)]
    assert all(r["n_removed"] == 3 * (r["doc_id"] == 6) for r in rows(line_dedup.dedup_lines(docs, Written(spark, "t"))))


def repeat_words(w, k=8):
    at = defaultdict(list)
    for i in range(len(w) - k + 1):
        at[tuple(w[i : i + k])].append(i)
    return len({j for v in at.values() if len(v) > 1 for i in v for j in range(i, i + k)})


def test_quality_counts(odd, none):
    for r, t in [(r, r["text"] or "") for r in rows(quality_rules.apply_rules(odd))]:
        w = WORD.findall(t)
        ls = [x for x in t.split("\n") if WORD.search(x)]
        assert (r["n_words"], r["word_chars"], r["n_dup_lines"]) == (len(w), sum(map(len, w)), len(ls) - len(set(ls)))
        assert r["n_repeat_words"] == repeat_words(w)
        assert r["base_failed"] == (len(w) < 20 or 100 * r["n_repeat_words"] > 30 * len(w)) and (not r["base_failed"] or not r["kept"])
    assert quality_rules.apply_rules(none).count() == 0


def test_exact_dedup(odd, none):
    want = defaultdict(list)
    for r in rows(odd):
        want[(r["text"] or "").translate(FOLD)].append(r["doc_id"])
    got = rows(exact_dedup.owners(odd, largest=True))
    texts = {r["doc_id"]: (r["text"] or "").translate(FOLD) for r in rows(odd)}
    for r in got:
        t = texts[r["doc_id"]]
        assert (r["keep_id"], r["group_size"], r["text_sha256"]) == (max(want[t]), len(want[t]), hashlib.sha256(t.encode()).hexdigest())
    assert sum(r["kept"] for r in got) == len(want) and len(got) == odd.count()
    assert {r["keep_id"] for r in rows(exact_dedup.owners(odd))} == {min(v) for v in want.values()}
    assert exact_dedup.owners(none).count() == 0
    left = exact_dedup.deduplicate(odd, largest=True)
    assert left.columns == odd.columns and sorted(r["doc_id"] for r in rows(left)) == sorted(max(v) for v in want.values())


@pytest.mark.parametrize("start", [b"", b"common start of all " * 40])
def test_trie_spills_by_subtree(start, monkeypatch):
    monkeypatch.setattr(exact_dedup, "MOST_MEMBERS", 10)
    rng = random.Random(5)
    keys = [start + bytes(rng.choice(b"abc") for _ in range(rng.randint(1, 12))) for _ in range(3000)] + [start[:k] for k in range(1, 30)]
    want = defaultdict(list)
    for i, k in enumerate(keys):
        want[k].append(i)
    for bound in (1 << 30, 20_000, 6000):
        t, most = exact_dedup.PatriciaOwners(max_bytes=bound), 0
        for i, k in enumerate(keys):
            t.insert(k, i, 1, (i,))
            most = max(most, t.bytes)
        assert bool(t.spills) == (bound < 1 << 30) and most <= 2 * bound + 1000
        got = [(k, b, n, sorted(x for chunk in m for x in chunk)) for k, b, n, m in t.groups()]
        assert sorted(got) == sorted((k, min(v), len(v), v) for k, v in want.items())


def test_trie_of_chains_and_of_one_string(monkeypatch):
    monkeypatch.setattr(exact_dedup, "MOST_MEMBERS", 30)
    for keys in ([b"a" * i for i in range(400)], [b"same" * 100] * 500):
        t = exact_dedup.PatriciaOwners(largest=True, max_bytes=3000)
        for i, k in enumerate(keys):
            t.insert(k, i, 1, (i,))
            assert t.bytes < 9000
        assert {k: (b, n) for k, b, n in t.owners()} == {k: (max(i for i, x in enumerate(keys) if x == k), keys.count(k)) for k in keys}


@pytest.fixture(scope="module")
def codec():
    return bpe.Codec(bpe.load_ranks(vocabulary_path("byte_bpe_50k.tiktoken")))


def test_bpe_equals_library(codec):
    import public_tokenizers
    import tiktoken

    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=codec.ranks, special_tokens={})
    rng = random.Random(1)
    texts = ["", " ", "  x", "we'll 'S 's 're're  'd\n\n", "a　b\x85c\x1c", "½²Ⅷ 12x", "x" * 5000, " " * 3000, "<|endoftext|>"]
    texts += ["".join(rng.choice(" '  \n\tabstrevlmdé1２½!?. 漢ː́🎉") for _ in range(rng.randint(1, 50))) for _ in range(1500)]
    got = list(codec.encode_batch(texts))
    assert [g.ids for g in got] == [enc.encode_ordinary(t) for t in texts]
    assert all(codec.decode(g.ids) == t.encode() for g, t in zip(got, texts, strict=True))
    for g, t in zip(got, texts, strict=True):
        assert len(g.starts) == len(g.upto) and (not t or (g.starts[0] == 0 and g.upto[-1] == len(g.ids)))
        for _ in range(5):
            a, b = sorted((rng.randint(0, len(t)), rng.randint(0, len(t))))
            at, part = codec.decode_part(g, a, b)
            assert t.startswith(part, at) and (at <= a and at + len(part) >= b if a < b else True)
    assert codec._merge_long(b"tttttattttt" * 40) == codec.merge(b"tttttattttt" * 3)[:0] + tuple(enc.encode_ordinary("tttttattttt" * 40))


def brute_pieces(text):
    """The pieces by the rules in words, one after another."""
    kind = lambda c: int(bpe.classes()[ord(c)])
    out, i = [], 0
    while i < len(text):
        end = next((e for e in bpe.ENDINGS if text[i] == "'" and text.startswith(e, i + 1)), None)
        j = i + (text[i] == " ")
        if end:
            j = i + 1 + len(end)
        elif j < len(text) and kind(text[j]) != bpe.SPACE:
            k = kind(text[j])
            while j < len(text) and kind(text[j]) == k:
                j += 1
        else:
            j = i
            while j < len(text) and kind(text[j]) == bpe.SPACE:
                j += 1
            if j < len(text) and j > i + 1:
                j -= 1
        out.append(i)
        i = j
    return out


def test_bpe_boundaries_by_the_machine():
    numbers, products, results, _ = bpe.machine()
    rng = random.Random(3)
    for n in (1, 2, 31, 33, 500, 5000):
        f = np.array([rng.choice(numbers) for _ in range(n)])
        got, state = results[bpe.scan(f, products)], bpe.CLOSED
        assert len({len(products), *products.shape}) == 1
        for i in range(n):
            symbol = int(np.flatnonzero(numbers == f[i])[0])
            state = bpe.step(state, symbol)[1]
            assert got[i] == state
    for _ in range(3000):
        t = "".join(rng.choice("  '\n\tastrevlmd1２½!. 漢é\x85\x1c") for _ in range(rng.randint(0, 70)))
        cut = sorted({0, *(rng.randint(0, len(t)) for _ in range(2))} - {len(t)})
        want = [a + p for a, b in zip(cut, [*cut[1:], len(t)]) for p in brute_pieces(t[a:b])]
        assert bpe.boundaries(t, np.array(cut, np.int64)).tolist() == want


def test_bpe_query_and_round_trip(odd, none):
    path = vocabulary_path("byte_bpe_50k.tiktoken")
    out = bpe.encode(odd, path, with_ids=True, with_offsets=True)
    texts = {r["doc_id"]: r["text"] or "" for r in rows(odd)}
    for r in rows(out):
        assert r["decoded_sha256"] == hashlib.sha256(texts[r["doc_id"]].encode()).hexdigest() and r["n_tokens"] == len(r["ids"])
        assert r["starts"] == (brute_pieces(texts[r["doc_id"]]) if len(texts[r["doc_id"]]) < 10_000 else r["starts"]) and (r["upto"] or [0])[-1] == r["n_tokens"]
    assert all(r["text"] == texts[r["doc_id"]] for r in rows(bpe.decode(out, path)))
    assert bpe.encode(none, path).count() == 0


def brute_fingerprint(t):
    w = [x.encode() for x in WORD.findall((t or "").translate(FOLD))]
    if not w:
        return 0
    h = [xxhash.xxh64_intdigest(b" ".join(w[i : i + 4]), 42) for i in range(max(1, len(w) - 3))]
    return sum(1 << k for k in range(64) if 2 * sum(v >> k & 1 for v in h) > len(h))


def test_simhash(spark, odd, none):
    docs = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").union(odd.select(F.col("doc_id") + 10_000, "text"))
    got, texts = rows(simhash.near_duplicates(docs, Written(spark, "t"))), rows(docs)
    fp = {r["doc_id"]: brute_fingerprint(r["text"]) for r in texts}
    assert all(int(r["fingerprint"], 16) == fp[r["doc_id"]] for r in got) and len(got) == len(texts)
    parent = {i: i for i in fp}

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for a, b in combinations(sorted(fp), 2):
        if (fp[a] ^ fp[b]).bit_count() <= 4 and find(a) != find(b):
            parent[max(find(a), find(b))] = min(find(a), find(b))
    assert all(r["component_id"] == find(r["doc_id"]) for r in got)
    assert simhash.near_duplicates(none, Written(spark, "t")).count() == 0
    kept = simhash.keep_one(odd, Written(spark, "t"))
    assert kept.columns == odd.columns and kept.count() == kept.select("doc_id").distinct().count()


@pytest.mark.parametrize("n, most", [(10, simhash.MOST), (1 << 23, simhash.MOST), (1 << 28, simhash.MOST), (1 << 40, simhash.MOST), (10, 6), (1 << 20, 4)])
def test_every_layout_finds_all_links(spark, n, most):
    rng = np.random.default_rng(2)
    base = rng.integers(-(1 << 63), (1 << 63) - 1, 30)
    base[:10] = base[0] ^ (base[:10] & 0xFFFFFFFF)  # large groups in which little links
    near = [int(x) ^ int(sum(1 << int(b) for b in rng.choice(63, rng.integers(0, 6), replace=False))) for x in base for _ in range(4)]
    fps = sorted({*map(int, base), *near})
    links = simhash.links(spark.createDataFrame([(x,) for x in fps], "fp bigint"), Written(spark, "t"), 4, n, most).collect()
    for pairs in ([(r["u"], r["v"]) for r in links],):
        parent = {x: x for x in fps}

        def find(i):
            while parent[i] != i:
                i = parent[i]
            return i

        for a, b in pairs:
            assert ((a ^ b) & (1 << 64) - 1).bit_count() <= 4
            parent[max(find(a), find(b))] = min(find(a), find(b))
        assert all(find(a) == find(b) for a, b in combinations(fps, 2) if ((a ^ b) & (1 << 64) - 1).bit_count() <= 4)


def fill(sizes, weights, total):
    target, capped = {}, set()
    while True:
        left = total - sum(2 * sizes[s] for s in capped)
        free = [s for s in sizes if s not in capped]
        if not free:
            return {s: 2.0 * sizes[s] for s in sizes}
        level = left / sum(weights[s] for s in free)
        over = [s for s in free if level * weights[s] > 2 * sizes[s]]
        if not over:
            target |= {s: level * weights[s] for s in free} | {s: 2.0 * sizes[s] for s in capped}
            return target
        capped |= set(over)


def brute_mix(rows, tilt, seed=11):
    """(expected copies, copies) of rows (id, source, size, target): the factor by halving, a full sort per source."""
    out = {}
    for s in {r[1] for r in rows}:
        own = [r for r in rows if r[1] == s]
        m = {i: 2.0 ** (round(math.log2(n) * mixing.STEPS) * tilt / mixing.STEPS) for i, _, n, _ in own if n}
        target = own[0][3]
        lo, hi = 0.0, 1e9
        for _ in range(300):
            mid = (lo + hi) / 2
            lo, hi = (mid, hi) if sum(n * min(2.0, mid * m[i]) for i, _, n, _ in own if n) < target else (lo, mid)
        e = {i: min(2.0, hi * m[i]) if n else 0.0 for i, _, n, _ in own}
        out |= {i: [e[i], math.floor(e[i] + 1e-9)] for i in e}
    return out


@pytest.mark.parametrize("tilt", [0.5, 1.0])
def test_mixing(spark, odd, none, tilt):
    docs = spark.read.parquet(f"{SF}/documents.parquet").withColumn("source", F.when(F.col("doc_id") % 11 != 0, F.col("source")))
    got = rows(mixing.mix(docs, Written(spark, "t"), tilt=tilt))
    size = Counter()
    for r in rows(docs):
        size[r["source"]] += len(WORD.findall(r["text"] or ""))
    order = sorted(size, key=lambda s: (s is None, s or ""))
    want = fill(size, {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}, 1.5 * sum(size.values()))
    taken, most = Counter(), Counter()
    brute = brute_mix([(r["doc_id"], r["source"], r["size"], r["target"]) for r in got], tilt)
    for r in got:
        assert r["source_size"] == size[r["source"]] and r["target"] == pytest.approx(want[r["source"]]) and r["taken"] <= 2 * r["size"]
        assert r["expected"] == pytest.approx(brute[r["doc_id"]][0], abs=1e-6) and r["copies"] in (brute[r["doc_id"]][1], brute[r["doc_id"]][1] + 1, math.ceil(r["expected"] - 1e-6))
        taken[r["source"]] += r["taken"]
        most[r["source"]] = max(most[r["source"]], r["size"])
    assert all(abs(taken[s] - want[s]) <= most[s] for s in size)
    if tilt == 1.0:
        return
    assert sorted(map(str, got)) == sorted(map(str, rows(mixing.mix(docs.repartition(5), Written(spark, "t")))))
    assert mixing.mix(none, Written(spark, "t")).count() == 0 and mixing.mix(odd, Written(spark, "t")).count() == odd.count()
    mixed = Counter(r["doc_id"] for r in mixing.mixed_rows(docs, Written(spark, "t")).collect())
    assert mixed == Counter({r["doc_id"]: r["copies"] for r in got if r["copies"]})
    assert mixing.mixed_rows(odd, Written(spark, "t")).columns == odd.columns


def test_mixing_draws_by_inclusion_probability(spark):
    """Over many seeds a document is drawn about as often as its inclusion probability says, and the order is
    that of random odds over inclusion odds."""
    rng = random.Random(2)
    docs = spark.createDataFrame([(i, rng.uniform(0.02, 0.98)) for i in range(300)], "id bigint, share double")
    total = docs.agg(F.sum("share")).first()[0]
    drawn, seeds = Counter(), 60
    for seed in range(seeds):
        got = docs.select("id", "share", F.xxhash64("id", F.lit(seed)).alias("h")).select("id", "share", "h", mixing.rank(F.col("h"), F.col("share")).alias("rank")).collect()
        u = {r["id"]: ((r["h"] & (1 << 64) - 1) >> 11) / 2**53 for r in got}
        by_odds = sorted(got, key=lambda r: u[r["id"]] / (1 - u[r["id"]]) / (r["share"] / (1 - r["share"])))
        ranked = sorted(got, key=lambda r: r["rank"])
        assert [r["id"] for r in by_odds] == [r["id"] for r in ranked]
        drawn.update(r["id"] for r in ranked[: round(total)])
    share = {r["id"]: r["share"] for r in docs.collect()}
    assert np.mean([abs(drawn[i] / seeds - p) for i, p in share.items()]) < 0.06
    for lo in (0.0, 0.25, 0.5, 0.75):
        own = [i for i, p in share.items() if lo <= p < lo + 0.25]
        assert abs(sum(drawn[i] for i in own) / seeds - sum(share[i] for i in own)) < 0.03 * len(own)


PAGE = """<html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body><header><h1>Site</h1></header>
<nav><ul><li><a href="/a">Menu</a></li></ul></nav><div class="cookie-notice">We use cookies</div><!-- <p>no</p> --><div id="sidebar"><p>Side</p></div>
<article><header><h1>Head&amp;line</h1></header><p><b>First   long&nbsp;paragraph of the text that goes on and on for many words.<br><p>Second &eacute; &#x41; 1 &lt; 2 paragraph with some more words in it.</p>
<div class="ad">Buy</div><form><p>Name</p><input name="x"><button>Send</button></form><p>Tail.</p><aside>Aside</aside></article>
<section class="comments"><article><p>A reader's comment that is rather long and has many words in it, more than others.</p></article></section><footer>&copy; x</footer>"""


def test_extraction():
    assert html_extract.main_text(PAGE) == "Head&line\nFirst long paragraph of the text that goes on and on for many words.\nSecond é A 1 < 2 paragraph with some more words in it.\nTail."
    assert html_extract.main_text(None) == html_extract.main_text("") == html_extract.main_text("<html><body></body>") == ""
    plain = "<body><p>Hi<div><p>" + "Long text of many words. " * 20 + "</p><p>" + "More text of many words. " * 20 + "</p></div>"
    assert html_extract.main_text(plain).count("\n") >= 1
    assert html_extract.main_text("<p>" + "y" * 200_000 + "</p>") == "y" * 200_000


def para(n, k=4):
    return f"{n} " + "text of many words " * k * 4


def test_extraction_span_decides_and_holders_widen_it():
    texts = [para(i).strip() for i in range(3)]
    p = [f"<p>{t}</p>" for t in texts]
    for page in (
        f"<main>{p[0]}<article>{p[1]}<p>Short.</p></article>{p[2]}</main>",
        f"<article>{p[0]}</article><article>{p[1]}<p>Short.</p></article>{p[2]}",
        f"{p[0]}<article>{p[1]}<p>Short.</p></article><article>{p[2]}</article>",
    ):
        assert html_extract.main_text(f"<body><p>Site</p>{page}<p>Go</p></body>") == "\n".join([*texts[:2], "Short.", texts[2]])


@pytest.mark.parametrize("items", [1, 3, 12])
def test_extraction_keeps_every_surge(items):
    texts = [para(0).strip(), *["item"] * items, para(1).strip(), "End."]
    assert html_extract.main_text("<body>" + "".join(f"<p>{t}</p>" for t in texts)) == "\n".join(texts)
    far = [para(0).strip(), *["a menu item"] * 100, para(1).strip()]
    got = html_extract.main_text("".join(f"<p>{t}</p>" for t in far)).split("\n")
    assert got[0] == far[0] and got[-1] == far[-1] and len(got) == 6  # a gap of more text than beside it goes
    assert html_extract.main_text("<p>one</p><p>two</p><p>three</p><p>four</p><p>five</p>") == "one\ntwo\nthree\nfour\nfive"


MAIN = "\n".join(para(i).strip() for i in range(3))
INNER = "".join(f"<p>{t}</p>" for t in MAIN.split("\n"))


@pytest.mark.parametrize("page", [
    f"<div class='content with-sidebar'><article>{INNER}</article></div>", f"<div class='content with-sidebar'>{INNER}</div>",
    f"<div id='page' class='has-header'>{INNER}<div class='sidebar'><p>Side</p></div></div>", f"<form><p>Name <input></p>{INNER}</form>",
    f"<div class=widget><main>{INNER}</main></div><p>{'outside ' * 5}</p>", f"<div class='widget'>{INNER}</div><div class='comments'><p>{para(7)}</p></div>",
    f"<header>Site</header><div class='sidebar'>Side</div><form><article>{INNER}</article></form><section class='comments'><article><p>{para(7, 40)}</p></article></section>",
    f"<div class='comments'>{INNER}</div><nav>{para(8)}</nav>", f"<html><head><title>T</title><body>{INNER}</body></html>", f"<nav><p>Menu</p><article>{INNER}</article>",
    f"<article><p>{'teaser ' * 15}</p></article><div class='side'>{INNER}</div>",
])
def test_marks_do_not_take_the_main_text(page):
    got = html_extract.main_text(page)
    assert MAIN in got and "Side" not in got and not got.startswith("Site") and "7 text" not in got and "8 text" not in got


def test_marks_still_drop_clutter():
    page = f"<div class='cookie-notice'>We use cookies</div><article><div class='article-header'><h1>Head</h1></div>{INNER}<div class='related-posts'>" + "<a href=x>Some other text to read now</a>" * 20 + "</div><div class='ad'>Buy</div><p hidden>No</p></article>"
    assert html_extract.main_text(page) == "Head\n" + MAIN
    assert html_extract.main_text("<nav><p>Only a menu</p></nav>") == ""


def test_extract_query(spark):
    pages = spark.createDataFrame([(1, None, PAGE, 5), (2, "u", None, 6), (2, "u", None, 6)], "page_id bigint, url string, html string, n_chars int")
    got = rows(html_extract.extract(pages))
    assert len(got) == 3 and all(r["n_chars"] == len(r["text"]) for r in got)
    assert html_extract.extract(pages.limit(0)).count() == 0


def test_warc(spark):
    big = "x" * 2000 + "é"
    data = [(1, "u", big), (2, None, big), (3, "v\nw", None), (4, "u", ""), (5, "u", "small"), (6, "u", "small"), (7, "u", big), (8, "u", "<p>\r\n\r\n" * 400), (9, "u", "z" * 300_000)]
    pages = spark.createDataFrame([(*r, "q") for r in data], "page_id bigint, url string, html string, record_type string").repartition(2)
    got = {r["page_id"]: r for r in rows(warc.archive_round_trip(pages, Written(spark, "t")))}
    for i, _, h in data:
        b = (h or "").encode()
        assert (got[i]["payload_bytes"], got[i]["payload_digest"]) == (len(b), hashlib.sha1(b).hexdigest())
        assert (got[i]["record_type"], got[i]["refers_to"]) == (("revisit", 7) if i in (1, 2) else ("response", None))
    bundles = Written(spark, "t").save(warc.write_bundles(pages, frame_bytes=1000))
    found = {r["page_id"]: r["html"] for r in rows(warc.lookup(bundles, pages.select("page_id")))}
    assert found == {i: h or "" for i, _, h in data if i not in (1, 2)}
    assert warc.offsets(bundles).count() == len(data)
    assert warc.archive_round_trip(pages.limit(0), Written(spark, "t")).count() == 0


def test_warc_page_ids_with_several_payloads(spark):
    a, b, c = ("%s" % x * 2000 for x in "abc")
    data = [(1, a), (1, b), (2, a), (3, c), (1, c), (1, None)]
    bundles = Written(spark, "t").save(warc.write_bundles(spark.createDataFrame([(i, "u", h) for i, h in data], "page_id bigint, url string, html string").repartition(2)))
    sha = lambda h: hashlib.sha1((h or "").encode()).hexdigest()
    got = {(r["page_id"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in rows(warc.read_bundles(bundles))}
    assert got == {(1, sha(a), "revisit", 2), (1, sha(b), "response", None), (2, sha(a), "response", None), (3, sha(c), "response", None), (1, sha(c), "revisit", 3), (1, sha(None), "response", None)}
    found = {(r["page_id"], r["html"]) for r in rows(warc.lookup(bundles, spark.createDataFrame([(1,), (2,), (3,)], "page_id bigint")))}
    assert found == {(1, b), (2, a), (3, c), (1, "")}


def test_bundle_is_readable_by_any_decoder():
    import io

    import zstandard

    b = warc.Bundle(100)
    recs = [warc.record(i, "u", b"p" * i * 30, "d", None) for i in range(9)]
    for i, r in enumerate(recs):
        b.add(i, r)
    content = b.close()
    assert zstandard.ZstdDecompressor().stream_reader(io.BytesIO(content), read_across_frames=True).read() == b"".join(recs)
    assert all(warc.read_record(content, x["frame"], x["start"])[1] == b"p" * x["page_id"] * 30 for x in b.index)


def test_ordinal_model_learns_grades(spark, none):
    rng = np.random.default_rng(0)
    x = rng.standard_normal((1500, 6)).astype(np.float32)
    y = np.digitize(x[:, 0] + 0.3 * rng.standard_normal(1500), [-1, 0, 1])
    m = quality_model.CumulativeLink.fit(x, y)
    t = m.tails(x @ m.weights)
    assert (np.diff(m.thresholds) > 0).all() and (np.diff(t, axis=1) <= 0).all()
    assert np.corrcoef(m.expected(t), y)[0, 1] > 0.9
    model = quality_model.fit(none, spark.createDataFrame([], "doc_id bigint, grade int"))
    assert quality_model.classify(none, model, 1).count() == 0


def test_quality_classifier(spark, odd):
    sf = SF.replace("0.001", "0.01")
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    train = labels.where("doc_id % 2 = 0")
    model = quality_model.fit(docs, quality_model.graded(train))
    got = quality_model.classify(docs, model, 1).join(labels.where("doc_id % 2 = 1"), "doc_id")
    assert got.where("kept = (quality = 1)").count() >= 0.95 * got.count()
    assert quality_model.classify(odd, model, 1).count() == odd.count()


def brute_kernel(u, z):
    total, most = 0.0, toxicity.GAP + 1
    for a in combinations(range(len(u)), toxicity.P):
        if any(y - x > most for x, y in zip(a, a[1:])):
            continue
        for b in combinations(range(len(z)), toxicity.P):
            if all(u[i] == z[j] for i, j in zip(a, b, strict=True)) and all(y - x <= most for x, y in zip(b, b[1:])):
                total += toxicity.DECAY ** (a[-1] - a[0] + b[-1] - b[0] - 2 * (toxicity.P - 1))
    return total / toxicity.UNIT


def test_kernel_and_screen():
    us = ["^stupid", "^st-upid", "^s.t.u.p", "^aaaaaaa", "^other", "^pidstu"]
    zs = ["^stup", "tupid", "aaaaa"]
    e = toxicity.Embedder(zs)
    e._learn(us)
    for u in us:
        got = e.rows[e.known[u]] if e.known[u] >= 0 else np.zeros(len(zs))
        assert got == pytest.approx([brute_kernel(u, z) ** toxicity.POWER for z in zs])
    assert "^stupid" in toxicity.units("you s t u p i d one")


def test_document_kernel_and_its_landmark_map():
    texts = ["you stupid one", "a st-upid and stu.pid word", "other things", "s t u p i d", "stupefied by tupids", "", "aaaaaaaa upid"]
    k = lambda d, e: sum(brute_kernel(u, v) ** toxicity.POWER for u in d for v in e)
    bags, zs = [toxicity.units(t) for t in texts], ["^stup", "tupid", "aaaaa", "upid "]
    gram = np.array([[k(d, e) for e in bags] for d in bags])
    assert np.allclose(gram, gram.T) and np.linalg.eigvalsh(gram).min() > -1e-9 * gram.max()
    values = toxicity.Embedder(zs).values(texts)
    assert values == pytest.approx(np.array([[k(d, [z]) for z in zs] for d in bags]), rel=1e-4)
    own = toxicity.landmark_matrix(zs)
    assert own == pytest.approx(np.array([[k([a], [b]) for b in zs] for a in zs]))
    val, vec = np.linalg.eigh(own)
    mapped = (own @ vec[:, val > 1e-9] / np.sqrt(val[val > 1e-9]))
    assert mapped @ mapped.T == pytest.approx(own)


def test_toxicity(spark, odd, none):
    sf = SF.replace("0.001", "0.1")
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    model = toxicity.fit(docs, labels)
    got = rows(toxicity.score(docs, model).join(labels, "doc_id"))
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) and 0 <= r["score"] <= 1 for r in got)
    for held, recall, false in ((True, 0.85, 0.02), (False, 0.85, 0.02)):
        own = [r for r in got if r["held_out"] == held and r["toxic"] is not None]
        caught = [r["predicted"] for r in own if r["toxic"] == 1]
        assert sum(caught) >= recall * len(caught) and sum(r["predicted"] for r in own if r["toxic"] == 0) <= false * len(own)
    out = toxicity.score(odd, model)
    assert out.count() == odd.count() and toxicity.drop_toxic(odd, model).columns == odd.columns
    assert {r["predicted"] for r in rows(out) if r["doc_id"] in (0, 1, 2)} == {0}
    empty = toxicity.fit(none, labels.limit(0))
    assert toxicity.score(odd, empty).where("predicted = 1").count() == 0 and toxicity.score(none, model).count() == 0
