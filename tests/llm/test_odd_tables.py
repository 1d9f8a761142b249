"""Every operator and stage on tables with repeated ids, null ids, dotted, map and clashing columns, and on none."""

import hashlib

import corpus_pipeline as pipeline
import pytest

from sparkspan.llm import bpe, exact_dedup, html_extract, line_dedup, mixing, quality_model, quality_rules, simhash, toxicity, warc
from sparkspan.llm.common import Written, vocabulary_path
from sparkspan.llm.queries import RANKS

SF = "/root/testdata/sf0.001"
EXTRA = "`a.b` int, m map<string,int>, row string, id string, no int, s string, h int, a int, b int, size string, draw int, copies int, toxic string, sha string, t int, w int, k int, x int, fp int, n_words string, `q``q` int"
DOCS = f"doc_id bigint, text string, lang string, source string, n_chars bigint, {EXTRA}"
COLS = 26


def words(n, k=90):
    return " ".join(f"{n}word{(i * 7919 + n * 31) % 997}" for i in range(k))


TEXTS = [(1, words(1)), (1, words(2)), (2, words(2).upper() + " END"), (None, words(3)), (None, words(3)), (None, words(4)), (None, None), (5, ""), (5, None), (6, words(1)), (6, words(1)), (7, "a\nb\nc"), (8, "a\nb\nc"), (8, "p\nq\nr\ns"), (None, "x\na\nb\nc"), (9, "é" * 50_000)]


@pytest.fixture(scope="module")
def odder(spark):
    rows = [(i, t, None, "s" if k % 3 else None, None, k, {"k": k} if k % 2 else None, *["z", "z", 1, "z", 1, 1, 1, "z", 1, 1, "z", "z", 1, 1, 1, 1, 1, "z", k % 2]) for k, (i, t) in enumerate(TEXTS)]
    return spark.createDataFrame(rows, DOCS).repartition(3)


def pairs(df):
    return sorted(((r["doc_id"], r["text"]) for r in df.collect()), key=str)


def fold(t):
    return (t or "").translate({c: c + 32 for c in range(65, 91)})


def test_lines_of_repeated_and_null_ids(odder, spark):
    got = line_dedup.dedup_lines(odder, Written(spark, "t"))
    left = pairs(got)
    assert got.count() == len(TEXTS)
    assert [t for i, t in left if i in (7, 8)] == ["a\nb\nc", "", "p\nq\nr\ns"] and (None, "x") in left
    assert sorted(t for i, t in left if i == 9) == ["é" * 50_000]


@pytest.mark.parametrize("with_counts", [True, False])
def test_rules(odder, with_counts):
    got = quality_rules.apply_rules(odder, with_counts=with_counts)
    assert got.count() == len(TEXTS) and {"a.b", "m", "row", "kept", "q`q"} <= set(got.columns)
    kept = {(r["doc_id"], r["text"]): r["kept"] for r in got.collect()}
    assert kept[1, words(1)] and not kept[7, "a\nb\nc"] and not kept[None, None]


def test_cascade_takes_the_measured_order(spark):
    """Dear rules that reject little come last, and the name is that of the first rule that holds."""
    docs = spark.createDataFrame([(i, words(i, 5 if i % 2 else 60) + "!" * (i % 3 * 40)) for i in range(200)], "doc_id bigint, text string")
    rules = quality_rules.default_rules()
    measured = quality_rules.ordered(quality_rules.measure(docs.select("text"), rules))
    assert [m.rate for m in measured] == sorted((m.rejects / m.cost for m in measured), reverse=True) and len(measured) == len(rules)
    place = [m.rule.name for m in measured]
    share = {m.rule.name: m.rejects for m in measured}
    assert share["too_short"] == pytest.approx(101 / 202) and place.index("too_short") < place.index("repeated_windows")
    out = docs.select("doc_id", quality_rules.cascade([m.rule for m in measured]).alias("name"), *[m.rule.fails.alias(f"f_{m.rule.name}") for m in measured]).collect()
    for r in out:  # each rule by itself tells what the cascade must name
        failed = [n for n in place if r[f"f_{n}"]]
        assert r["name"] == (failed[0] if failed else None) and r["f_too_short"] == (r["doc_id"] % 2 == 1)
    assert len({r["name"] for r in out}) > 2
    symbols = spark.createDataFrame([(1, "a#b*c$d%e&f|g<h>i@j!k"), (2, "plain")], "doc_id bigint, text string")
    assert [r["n_symbols"] for r in quality_rules.apply_rules(symbols).orderBy("doc_id").collect()] == [8, 0]


def test_archive(spark):
    big, other = "x" * 2000, "y" * 3000
    data = [(1, big), (None, big), (None, other), (None, other), (2, big), (None, None), (2, other)]
    pages = spark.createDataFrame([(i, None, h, 1) for i, h in data], "page_id bigint, url string, html string, `a.b` int")
    bundles = Written(spark, "t").save(warc.write_bundles(pages))
    sha = lambda h: hashlib.sha1((h or "").encode()).hexdigest()
    got = sorted(((r["page_id"], r["payload_digest"], r["record_type"], r["refers_to"]) for r in warc.read_bundles(bundles).collect()), key=str)
    want = [(1, sha(big), "revisit", 2), (2, sha(big), "response", None), (2, sha(other), "response", None), (None, sha(None), "response", None), (None, sha(big), "revisit", 2), (None, sha(other), "revisit", 2), (None, sha(other), "revisit", 2)]
    assert got == sorted(want, key=str)
    asked = spark.createDataFrame([(1,), (2,), (2,), (None,), (99,)], "page_id bigint")
    assert sorted(r["html"] for r in warc.lookup(bundles, asked).collect()) == [big, other] and warc.lookup(bundles.limit(0), asked).count() == 0
    nothing = warc.archive_round_trip(pages.limit(0), Written(spark, "t"))
    assert nothing.count() == 0


def test_exported_bundles_are_files(spark, tmp_path):
    pages = spark.createDataFrame([(i, "u", f"<p>{i}</p>" * 300) for i in range(30)], "page_id bigint, url string, html string")
    bundles = Written(spark, "t").save(warc.write_bundles(pages, frame_bytes=2000, bundle_bytes=500))
    warc.export(bundles, str(tmp_path))
    names = {r["bundle"]: r["content"] for r in bundles.collect()}
    assert {p.name: p.read_bytes() for p in tmp_path.iterdir()} == names and len(names) > 1
    warc.export(bundles.limit(0), str(tmp_path))


def test_exact_copies(odder):
    groups: dict = {}
    for i, t in TEXTS:
        groups.setdefault(fold(t), []).append(i)
    best = {t: max((i for i in ids if i is not None), default=None) for t, ids in groups.items()}
    for r in exact_dedup.owners(odder, largest=True).collect():
        t = next(t for t in groups if hashlib.sha256(t.encode()).hexdigest() == r["text_sha256"])
        assert (r["keep_id"], r["group_size"]) == (best[t], len(groups[t])) and r["doc_id"] in groups[t]
    left = exact_dedup.deduplicate(odder, largest=True)
    assert left.columns == odder.columns and sorted(((i, fold(t)) for i, t in pairs(left)), key=str) == sorted(((i, t) for t, i in best.items()), key=str)
    again = exact_dedup.deduplicate(odder.repartition(7), largest=True)
    assert sorted(map(str, left.collect())) == sorted(map(str, again.collect()))  # of equal rows the same stays


def test_near_copies_and_mixing(odder, spark):
    exact = exact_dedup.deduplicate(odder, largest=True)
    near = simhash.keep_one(exact, Written(spark, "t"))
    assert near.columns == odder.columns and set(pairs(near)) <= set(pairs(exact))
    assert {fold(t) for _, t in pairs(near)} >= {fold(words(1)), fold(words(3)), fold(words(4)), "é" * 50_000}
    assert simhash.near_duplicates(odder, Written(spark, "t")).count() == len(TEXTS)
    taken = mixing.mix(odder, Written(spark, "t"))
    rows = mixing.mixed_rows(odder, Written(spark, "t"))
    assert taken.count() == len(TEXTS) and rows.columns == odder.columns and rows.count() == sum(r["copies"] for r in taken.collect())


def test_codec_extraction_and_models(odder, spark):
    path = vocabulary_path(RANKS)
    out = bpe.encode(odder, path, with_ids=True)
    assert sorted(map(str, pairs(bpe.decode(out, path)))) == sorted(str((i, t or "")) for i, t in TEXTS)
    pages = odder.selectExpr("doc_id as page_id", "lang as url", "text as html", "`a.b`", "m")
    assert html_extract.extract(pages).count() == len(TEXTS)
    labels = spark.createDataFrame([(i, g) for i in (1, 2, 6, 7, 8, None) for g in ((0, 1, None) if i == 1 else (i and i % 2,))], "doc_id bigint, grade int")
    model = quality_model.fit(odder, labels)
    got = quality_model.classify(odder, model, 1).collect()
    assert len(got) == len(TEXTS) and all(0 <= r["tail"] <= 1 for r in got)
    model = toxicity.fit(odder, labels, label_col="grade")
    assert toxicity.score(odder, model).count() == len(TEXTS)
    left = toxicity.drop_toxic(odder, model)
    assert left.columns == odder.columns and set(pairs(left)) <= set(pairs(odder))


@pytest.mark.parametrize("empty", [False, True])
def test_stages(odder, spark, empty):
    now = odder.limit(0) if empty else odder
    for name, stage in pipeline.STAGES:
        out = Written(spark, "p").save(stage(spark, now, SF))
        assert name == "byte_bpe" or out.columns == odder.columns
        assert out.count() == 0 if empty else out.count() > 0
        if name in ("toxicity", "exact_dedup"):  # clean rows stay: these texts hold no insult
            assert {fold(t) for _, t in pairs(out)} == {fold(r["text"]) for r in now.collect()}
        now = out
