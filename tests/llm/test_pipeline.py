"""The pipeline's stages on planted cases: each decision takes effect and clean documents stay."""

from fairsummary.llm.common import materialize

import corpus_pipeline

DATA = "/root/testdata/sf0.001"


def test_stages(spark):
    docs = spark.read.parquet(f"{DATA}/documents.parquet")
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES:
        before = docs.count()
        docs = materialize(stage(spark, docs, DATA), name)
        if name != "packing":
            assert docs.columns == columns
            assert docs.count() <= before if name in ("toxicity", "near_dedup") else docs.count() == before
    assert docs.where("bin IS NULL AND n_tokens > 0").count() == 0


def test_near_copies_go_and_clean_documents_stay(spark):
    base = [" ".join(f"t{k}x{i}" for i in range(200)) for k in range(6)]
    near = base[0].replace("t0x100", "changed")
    rows = [(i, t, "en", "s", len(t)) for i, t in enumerate([*base, near, base[1], base[2] + " more"])]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    kept = sorted(r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, DATA).collect())
    assert kept == [0, 1, 2, 3, 4, 5]


def test_near_copies_are_found_by_fingerprint(spark, monkeypatch):
    from fairsummary.llm import simhash

    base = [" ".join(f"t{k}x{i}" for i in range(2000)) for k in range(4)]
    rows = list(enumerate([*base, base[0].replace("t0x1000 ", "changed "), base[1] + " more"]))
    texts = materialize(spark.createDataFrame(rows, "node bigint, text string"), "texts")
    assert {(r.a, r.b) for r in simhash.fingerprint_links(texts).collect()} == {(0, 4), (1, 5)}
    asked, links = [], simhash.links
    monkeypatch.setattr(simhash, "links", lambda *a, **k: asked.append(a[1]) or links(*a, **k))
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in rows], COLUMNS)
    assert sorted(r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, DATA).collect()) == [0, 1, 2, 3] and asked == [simhash.NEAR]


def test_near_copies_are_looked_for_in_small_batches(spark, tmp_path, monkeypatch):
    """Texts of one partition together exceed a batch by far; the setting is as before at the end."""
    from fairsummary.llm import common, simhash

    key, slices, seen = "spark.sql.execution.arrow.maxBytesPerBatch", simhash.text_slices, tmp_path / "seen"

    def noted(batch, *a):
        with seen.open("a") as f:
            f.write(f"{batch.nbytes}\n")
        return slices(batch, *a)

    monkeypatch.setattr(simhash, "text_slices", noted)
    before = spark.conf.get(key)
    docs = spark.range(0, 2400, 1, 1).selectExpr("id doc_id", "array_join(transform(sequence(0, 999), i -> concat('w', i, 'x', least(id, 2398))), ' ') text", "'en' lang", "'s' source", "0L n_chars")
    assert docs.selectExpr("sum(length(text))").first()[0] > 4 * common.BATCH_BYTES
    assert simhash.keep_one(docs).count() == 2399
    sizes = [int(x) for x in seen.read_text().split()]
    assert sum(sizes) > 4 * common.BATCH_BYTES and max(sizes) < 1.25 * common.BATCH_BYTES
    assert spark.conf.get(key) == before


COLUMNS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def _rows(spark, texts):
    return spark.createDataFrame([(i, t, "en", f"s{i % 3}", None if t is None else len(t)) for i, t in enumerate(texts)], COLUMNS)


def test_toxic_documents_go(spark, tmp_path):
    texts = [("you are an idiot today" if i % 3 == 0 else "what a lovely morning today") + f" n{i}" for i in range(120)] + [None, "", "such an idiott"]
    spark.createDataFrame([(i, 0, int(i % 3 == 0)) for i in range(120)], "doc_id bigint, quality int, toxic int").write.parquet(str(tmp_path / "labels.parquet"))
    kept = {r.doc_id for r in corpus_pipeline.drop_toxic(spark, _rows(spark, texts), str(tmp_path)).collect()}
    assert kept >= {i for i in range(120) if i % 3} | {120, 121} and not kept & set(range(0, 120, 3))


def test_repeated_passages_are_cut(spark):
    passage = " ".join(f"p{i}" for i in range(60))
    texts = [f"one {passage} end", f"two {passage} more", "short and clean text", None, "", f"{passage} {passage}"]
    got = {r.doc_id: r for r in corpus_pipeline.cut_repeats(spark, _rows(spark, texts), DATA).collect()}
    assert [got[i].text for i in range(6)] == ["one end", "two more", texts[2], None, "", ""]
    assert got[0].n_chars == 7 and got[2].n_chars == len(texts[2]) and got[3].n_chars is None


def test_personal_data_is_replaced(spark):
    texts = ["write to bob.lee@host.org now", "call +1 (555) 555-1000", "nothing here", None, "4111 1111 1111 1111 and 10.0.0.7"]
    got = {r.doc_id: r for r in corpus_pipeline.redact_personal(spark, _rows(spark, texts), DATA).collect()}
    assert [got[i].text for i in range(5)] == ["write to [EMAIL] now", "call [PHONE]", "nothing here", None, "[CARD] and [IP]"]
    assert got[0].n_chars == len(got[0].text) and got[3].n_chars is None


def test_documents_are_packed(spark):
    from fairsummary.llm import packing

    texts = ["a " * 1500, "b " * 1400, "c " * 500, "d " * 5000, None, "same text", "same text"]
    rows = [(i, t, "en", s, 0) for i, (t, s) in enumerate(zip(texts, ["x", "x", "y", "z", "x", "u", "v"]))]
    got = corpus_pipeline.pack_documents(spark, spark.createDataFrame(rows, COLUMNS), DATA).toPandas()
    pieces = sorted(((n, d, p, rows[d][3], rows[d][1]) for d, p, n in zip(got.doc_id, got.piece, got.n_tokens) if n), key=lambda x: (-x[0], x[1], x[2]))
    want = packing.brute_force([x[0] for x in pieces], [x[3] for x in pieces], [x[4] for x in pieces], packing.CAPACITY)
    assert {(x[1], x[2]): b for x, b in zip(pieces, want)} == {(r.doc_id, r.piece): r.bin for r in got.dropna().itertuples()}
    assert got[got.doc_id == 4].bin.isna().all()


def test_awkward_tables_pass_every_stage(spark):
    rows = [(1, "a b c", "en", "s", 5), (1, "a b c", "en", "s", 5), (None, "x y", None, None, None), (2, None, "en", "s", 0)]
    for docs in (spark.createDataFrame([], COLUMNS), spark.createDataFrame(rows, COLUMNS)):
        wide = docs.selectExpr("*", "'clash' AS score", "'clash' AS node", "'clash' AS kept_text")
        for name, stage in corpus_pipeline.STAGES:
            got = materialize(stage(spark, wide, DATA), name)
            n = got.count() if name != "packing" else got.select("doc_id").count()
            assert n == {"near_dedup": min(3, docs.count())}.get(name, docs.count()), name
            if name != "packing":
                assert got.columns == docs.columns
