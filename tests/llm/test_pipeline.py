import corpus_pipeline as pipeline

from sparkspan.llm import exact_dedup, mixing, simhash
from sparkspan.llm.common import Written, table

SF = "/root/testdata/sf0.001"


def test_stages_against_brute_force(spark):
    docs = table(spark, SF, "documents")
    counts, now = [], docs
    for name, stage in pipeline.STAGES:
        out = Written(spark, "p").save(stage(spark, now, SF))
        rows = [r.asDict() for r in out.collect()]
        before = [r.asDict() for r in now.collect()]
        if name != "byte_bpe":
            assert out.columns == docs.columns
        ids = {r["doc_id"] for r in rows}
        if name == "exact_dedup":
            fold = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
            best: dict = {}
            for r in before:
                t = (r["text"] or "").translate(fold)
                best[t] = max(best.get(t, -1), r["doc_id"])
            assert ids == set(best.values()) and len(rows) == len(best)
        if name == "near_dedup":
            fps = {r["doc_id"]: simhash.fingerprint((r["text"] or "").lower()) for r in rows}
            assert len(ids) == len(rows) and all((a ^ b).bit_count() > 4 for i, a in fps.items() for j, b in fps.items() if i < j)
        if name == "mixing":
            per = {i: sum(r["doc_id"] == i for r in rows) for i in ids}
            words = lambda rs: sum(len((r["text"] or "").split()) for r in rs)
            assert max(per.values()) <= 2 and abs(words(rows) / words(before) - 1.5) < 0.3
        if name == "byte_bpe":
            assert len(rows) == len(before) and all(r["n_tokens"] == len(r["ids"]) for r in rows)
        counts.append(len(rows))
        now = out
    assert counts[0] <= docs.count() and counts[1] <= counts[0] and counts[2] <= counts[1]
    assert pipeline.run(spark, SF).count() == counts[-1]


def test_rows_with_null_ids_and_ids_with_two_texts_stay(spark):
    text = lambda n: " ".join(f"{n}word{(i * 7919 + n * 31) % 997}" for i in range(120))
    data = [(1, text(1)), (1, text(2)), (2, text(2) + " end"), (None, text(3)), (None, text(4)), (5, text(5)), (None, text(5)), (None, text(6)), (None, text(6)), (7, text(1))]
    docs = spark.createDataFrame([(i, t, None if n % 3 else "s") for n, (i, t) in enumerate(data)], "doc_id bigint, text string, source string").repartition(3)
    for largest in (True, False):
        exact = exact_dedup.deduplicate(docs, largest=largest)
        want = {*data} - {(None, text(5))} - {(1, text(1)) if largest else (7, text(1))}
        assert sorted(map(str, exact.select("doc_id", "text").collect())) == sorted(str(r) for r in spark.createDataFrame(list(want), "doc_id bigint, text string").collect())
    near = simhash.keep_one(exact, Written(spark, "t"))
    got = {(r["doc_id"], r["text"]) for r in near.collect()}
    assert got == {(1, text(1)), (1, text(2)), (None, text(3)), (None, text(4)), (5, text(5)), (None, text(6))} and near.count() == 6
    mixed = {(r["doc_id"], r["text"]) for r in mixing.mixed_rows(near, Written(spark, "t")).collect()}
    taken = mixing.mix(near, Written(spark, "t")).where("copies > 0")
    rows = mixing.mixed_rows(near, Written(spark, "t"))
    assert mixed <= got and taken.count() == len(mixed) and any(i is None for i, _ in mixed)
    assert sum(r["copies"] for r in taken.collect()) == rows.count()
