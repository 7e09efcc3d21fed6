"""Every text operator against brute force, an exact round trip or held-out accuracy, with awkward rows."""

import hashlib
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from fairsummary.llm import lattice, media, neighbours, packing, personal, piece_counts, simhash, substring, token_table, toxicity
from fairsummary.llm.common import Memory

DATA = "/root/testdata/sf0.001"
PASSAGE = " ".join(f"w{i}" for i in range(50))
TEXTS = [None, "", "   \n\t ", PASSAGE, f"x y {PASSAGE} z", PASSAGE, "a " * 100, "naïve café 😀 ﬁn İstanbul ΣΑΣ 北京 á", "don't, won't! 1234 <|endoftext|> foo.bar baz\x1cq", "word " * 3000 + "tail", "▁x", "  two  spaces\r\n"]


def table(spark, texts=TEXTS):
    rows = [(i, t, "en", "src0", len(t or "")) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")


def docs(spark):
    return spark.read.parquet(f"{DATA}/documents.parquet")


@pytest.mark.parametrize("bits", [substring.FILTER_BITS, 1])
def test_substring_dedup(spark, bits):
    t = table(spark).withColumn("n_words", F.lit("clash"))
    got = sorted(substring.remove_repeats(t, filter_bits=bits).select("doc_id", "n_words", "n_removed", "kept_text").collect())
    want = substring.brute_force(TEXTS)
    assert [(r.n_words, r.n_removed, hashlib.sha256(r.kept_text.encode()).hexdigest()) for r in got] == want
    assert substring.remove_repeats(table(spark, [])).count() == 0
    assert all(substring.is_cover(p, c) for p, c in substring.COVERS.items())
    for window in (1, 5, 12):
        got = sorted(substring.remove_repeats(table(spark), window=window).select("doc_id", "n_removed").collect())
        assert [r.n_removed for r in got] == [w[1] for w in substring.brute_force(TEXTS, window)]


def test_media_round_trip(spark):
    got = {r.doc_id: r for r in media.digest(table(spark)).collect()}
    for i, t in enumerate(TEXTS):
        raw = (t or "").encode()
        body = raw + bytes(max(64, -(-len(raw) // 64) * 64) - len(raw))
        assert (got[i].n_bytes, got[i].payload_bytes, got[i].payload_sha256, got[i].tail_crc32) == (len(raw), len(body), hashlib.sha256(body).hexdigest(), zlib.crc32(body[-64:]))
        m = media.wrap(body, 64)
        tag, rate, _, data = media.parse_wave(m)
        pcm = media.resample(media.samples_of(m)[0], rate, 8000)  # each file by itself; the query decodes blocks of many files together
        assert data == body and (got[i].media_bytes, got[i].media_sha256) == (len(m), hashlib.sha256(m).hexdigest())
        assert got[i].feature == f"codec={tag};{media.describe(pcm, 8000)}" and (got[i].pcm_bytes, got[i].pcm_crc32) == (2 * len(pcm), zlib.crc32(pcm.astype("<i2").tobytes()))
    assert {r.feature.split(";")[0] for r in media.digest(docs(spark)).collect()} == {"codec=6", "codec=7", "codec=17"}
    assert media.digest(table(spark, [])).count() == 0
    again = media.digest(table(spark, [PASSAGE, PASSAGE, None, ""])).drop("doc_id").collect()
    assert again[0] == again[1] and again[2] == again[3]
    for tag in media.CODECS:
        one = media.media_features(media.store_payload(table(spark, [PASSAGE]).withColumn("media", F.lit("clash")), tag=tag), keep_pcm=True).first()
        assert media.parse_wave(bytes(one.media))[0] == tag and media.parse_wave(bytes(one.pcm))[0] == media.PCM
    for table_, tag in ((media.MULAW_TABLE, media.MULAW), (media.ALAW_TABLE, media.ALAW)):
        assert (media.expand(media.encode_companded(table_, tag), tag) == table_).all()
    assert (media.MULAW_TABLE[0], media.MULAW_TABLE[128], media.ALAW_TABLE[0x55], media.ALAW_TABLE[0xD5]) == (-32124, 32124, -8, 8)
    pcm = (8000 * np.sin(np.arange(2000) / 9)).astype(np.int16)
    coded = media.encode_ima(pcm)
    out = media.decode_ima(coded)[:2000]
    assert np.abs(out.astype(int) - pcm).mean() < 300
    single = np.concatenate([media.decode_ima(coded[i : i + 256]) for i in range(0, len(coded), 256)])
    assert (single[:2000] == out).all()
    assert len(media.resample(pcm, 8000, 16000)) == 4000
    bad = spark.createDataFrame([(None,), (b"junk",)], "media binary")
    assert [r.payload_bytes for r in media.media_features(bad).collect()] == [None, None]


def test_token_table(spark):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(token_table.vocabulary("word_bpe_49k.json"))
    start = 0
    for r in sorted(token_table.digest(table(spark)).collect()):
        ids = t.encode(TEXTS[r.doc_id] or "", add_special_tokens=False).ids + [1]
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    path = token_table.new_path(spark, "tokens")
    token_table.write_token_table(docs(spark), path, delta=True)
    some = token_table.read_token_table(spark, path, doc_ids=[3, 5])
    assert sorted(r.doc_id for r in some.collect()) == [3, 5]
    assert "ids" not in token_table.read_token_table(spark, path, ids=False).columns


def test_piece_counts(spark):
    pieces = set(piece_counts.model_pieces(token_table.vocabulary("piece_bpe_32k.model")))
    got = {r.doc_id: r for r in piece_counts.digest(table(spark)).collect()}
    for i, t in enumerate(TEXTS):
        assert (got[i].n_words, got[i].n_tokens, got[i].n_unknown) == piece_counts.brute_force(t, pieces), t
    auto = piece_counts.Automaton(["▁a", "▁abc", "b", "cd", "▁"])
    assert [auto.count("▁" + w) for w in ("ab", "abcd", "abcx", "b")] == [2, -1, -1, 2]  # greedy takes "▁abc" and never goes back


def _best_cut(word, score, unknown):
    """Plain search of the largest sum; of equal sums the last piece that starts first."""
    best = [(0.0, [])]
    for end in range(1, len(word) + 1):
        options = [(best[i][0] + score[word[i:end]], best[i][1] + [word[i:end]]) for i in range(end) if word[i:end] in score]
        if word[end - 1] not in score:
            options.append((best[end - 1][0] + unknown, best[end - 1][1] + [word[end - 1]]))
        best.append(max(options, key=lambda o: o[0]))
    return best[-1][1]


def _as_lattice_model(path):
    """The model file with its type switched from merges to the lattice, by rewriting one field of its settings."""

    def number(b, i):
        v = s = 0
        while True:
            v, s, i = v | (b[i] & 127) << s, s + 7, i + 1
            if b[i - 1] < 128:
                return v, i

    def coded(v):
        out = b""
        while v > 127:
            out, v = out + bytes([v & 127 | 128]), v >> 7
        return out + bytes([v])

    def fields(b):
        i = 0
        while i < len(b):
            at = i
            key, i = number(b, i)
            body = None
            if key & 7 == 0:
                _, i = number(b, i)
            elif key & 7 == 2:
                n, i = number(b, i)
                body, i = b[i : i + n], i + n
            else:
                i += 4 if key & 7 == 5 else 8
            yield key >> 3, b[at:i], body

    out = b""
    for field, whole, body in fields(open(path, "rb").read()):
        if field == 2:  # trainer settings; their field 3 is the model type, and 1 means a lattice
            body = b"".join(w for f, w, _ in fields(body) if f != 3) + bytes([3 << 3, 1])
            whole = bytes([2 << 3 | 2]) + coded(len(body)) + body
        out += whole
    return out


def test_lattice_against_the_library(spark):
    """The library's search over all cuts finds the same words; its faster search never finds a larger sum."""
    import sentencepiece

    path = token_table.vocabulary("piece_bpe_32k.model")
    model, library = lattice.Lattice.from_model(path), sentencepiece.SentencePieceProcessor(model_proto=_as_lattice_model(path))
    score = lambda ids: sum(library.get_score(i) for i in ids)
    texts = [r.text for r in docs(spark).orderBy("doc_id").collect() if r.text]
    words = sorted({w for t in texts for w in lattice.segments(t) if w.startswith("▁") and not w.startswith("▁▁")})[::7]
    known = [w for w in words if all(library.piece_to_id(c) != library.unk_id() for c in w)]
    assert len(known) > 500
    for word in known:
        own = np.frombuffer(model.encode_words([word])[0], "<u4").tolist()
        text = word[1:]
        best = library.nbest_encode_as_ids(text, 2)[0]
        assert best == own or score(best) == score(own), word
        assert score(own) >= score(library.encode(text)), word


def test_lattice(spark):
    got = {r.doc_id: r for r in lattice.digest(table(spark)).collect()}
    assert all(r.round_trip == (i != 10) for i, r in got.items())
    path = token_table.vocabulary("piece_bpe_32k.model")
    model = lattice.Lattice.from_model(path)
    score = {model.pieces[slot]: float(v) for slot, v in zip(model.slot, model.scores)}
    number = dict(zip(model.pieces, model.ids.tolist()))
    words = {w for t in [t for t in TEXTS if t and len(t) < 500] + [r.text for r in docs(spark).limit(20).collect()] for w in lattice.segments(t)}
    for word, ids in zip(words, model.encode_words(list(words))):
        want = [i for p in _best_cut(word, score, model.unknown) for i in ([number[p]] if p in number else [model.byte_ids[v] for v in p.encode()])]
        assert np.frombuffer(ids, "<u4").tolist() == want, word


def test_personal_data(spark):
    texts = ["a@b.c..d@e.f x@y.z@q.r", "1.2.3.4.5.6.7.8 300.1.1.1 0001.2.3.4", "4111 1111 1111 1111", "4111 1111 1111 1111 1111", "x4111111111111111y +1 (988) 555-2485", "é😀 a@b.c 😀 1.2.3.4", "9-4111111111111111 - 4111111111111111", "5 5 5 5 " * 500, None, ""]
    got = {r.doc_id: r for r in personal.digest(table(spark, texts)).collect()}
    for i, t in enumerate(texts):
        spans = ",".join(f"{k}:{a}:{b}" for k, a, b in personal.brute_force(t))
        assert got[i].base_sha256 == hashlib.sha256(spans.encode()).hexdigest(), t
        assert got[i].spans.startswith(spans)
    red = {r.doc_id: r.text for r in personal.redact(table(spark, texts)).collect()}
    assert red[2] == "[CARD]" and red[8] is None
    known = [f"please call +1 (555) 555-{1000 + i} now" for i in range(8)] + ["please call 99-1234-77 now", "nothing 99-1234-88 here"]
    found = {r.doc_id: r.spans for r in personal.digest(table(spark, known)).collect()}
    assert personal.digest(table(spark, [])).count() == 0 and found[9] == ""


def test_personal_data_contexts(spark):
    texts = [f"please call +1 (555) 555-{1000 + i} now" for i in range(8)] + ["please call 99-1234-77 now", "nothing 99-1234-88 here"]
    texts += [f"or write to <user{'abcdefgh'[i]}@host.org> today" for i in range(8)] + ["or write to <someone@intranet> today", "or write to me"]
    texts += [f"pay with card 4111 1111 1111 {d} then" for d in ("1111", "1129", "1137", "1145")] + ["pay with card 77 88 99 then", "pay with card x9, bob@host.org and 12"]
    # each pattern shares three of its five tokens with the one before, so one more is trusted in each round
    texts += [f"{'uvwxyz'[r]} has n{j} end" for r in range(6) for j in range(2 * r, 2 * r + 5)]
    texts += [f"u has seed{'abcdefghi'[i]}@host.org end" for i in range(9)]
    got = {r.doc_id: r.spans for r in personal.digest(table(spark, texts)).collect()}
    assert got[8] == "identifier:12:22" and got[9] == "" and got[19] == ""
    assert got[18] == "identifier:13:29" and got[24] == "identifier:14:22" and got[25].endswith("identifier:14:16")
    assert all(got[i].startswith("identifier:6:") for i in range(26, 56))


def test_toxicity_held_out(spark):
    rows = [("you are an idiot today" if i % 3 == 0 else "what a lovely morning today") + f" n{i}" for i in range(120)]
    t = table(spark, [*rows, None, "such an idiott"])
    labels = spark.createDataFrame([(i, i % 2, int(i % 3 == 0)) for i in range(120)], "doc_id bigint, quality int, toxic int")
    got = {r.doc_id: r for r in toxicity.digest(t, labels).collect()}
    assert all(r.held_out == (zlib.crc32(str(i).encode()) % 3 == 1) for i, r in got.items())
    assert all(got[i].predicted == int(i % 3 == 0) for i in range(120)) and got[120].predicted == 0
    assert got[121].score > got[1].score
    assert toxicity.digest(t, labels.where("false")).where("predicted = 1").count() == 0


def test_toxicity_rare_terms(spark):
    rng = np.random.default_rng(3)
    rows = []
    for i in range(1500):  # one text in 150 has a toxic term of its own
        filler = " ".join(f"w{x}" for x in rng.integers(0, 40, 12))
        rows.append(f"{filler} " + (("zyxquork" if i % 150 == 0 else "idiot") if i % 3 == 0 else "morning") + f" {filler}")
    labels = spark.createDataFrame([(i, 0, int(i % 3 == 0)) for i in range(1500)], "doc_id bigint, quality int, toxic int")
    got = {r.doc_id: r for r in toxicity.digest(table(spark, rows), labels).collect()}
    rare = [got[i].predicted for i in range(0, 1500, 150) if got[i].held_out]
    assert len(rare) > 1 and np.mean(rare) >= 0.8
    assert np.mean([got[i].predicted for i in range(1500) if i % 3]) < 0.05


def test_neighbours(spark):
    rng = np.random.default_rng(1)
    X = rng.normal(size=(900, 8)).astype(np.float32)
    X[300:600] = X[300]
    rows = [(i, x.tolist()) for i, x in enumerate(X)] + [(1000, None), (1100, [0.0] * 8), (1200, [float("nan")] * 8), (1300, [1.0])]
    e = spark.createDataFrame(rows, "vec_id bigint, embedding array<float>")
    got, hits, total = neighbours.digest(e).collect(), 0, 0
    D = X.astype(float)
    for q in range(0, 900, 100):
        d = np.sqrt(((D - D[q]) ** 2).sum(1))
        d[q] = np.inf
        want = np.lexsort((np.arange(900), d))[:10]
        mine = sorted((r.rank, r.vec_id, r.score) for r in got if r.query_id == q)
        assert [m[0] for m in mine] == list(range(1, 11)) and all(abs(s - d[v]) < 1e-12 for _, v, s in mine)
        hits, total = hits + len({v for _, v, _ in mine} & set(want.tolist())), total + 10
    assert hits / total >= 0.9 and {r.query_id for r in got} == set(range(0, 900, 100))
    assert neighbours.digest(e.where("false")).count() == 0
    # a small top, so leaves are split below it; one position holds a third of the rows and cannot be
    small = neighbours.Settings(sample=128, leaf=16, full=24, fit=64, beam=4)
    deep = neighbours.search(e, s=small).collect()
    truth = {(r.query_id, r.vec_id) for r in got}
    assert len(deep) == len(got) and len(truth & {(r.query_id, r.vec_id) for r in deep}) >= 0.9 * len(truth)


def _components(fps, bits):
    near = np.bitwise_count(fps[:, None] ^ fps[None]) <= bits
    label = np.arange(len(fps))
    while (new := np.array([label[n].min() for n in near])).tolist() != label.tolist():
        label = new
    return label


@pytest.mark.parametrize("crowd", [48, 1])
def test_simhash_links(spark, crowd):
    rng = np.random.default_rng(2)
    base = rng.integers(0, 2**63, 40)
    fps = np.unique(np.concatenate([base, *[base ^ (1 << int(rng.integers(0, 62))) ^ (1 << int(rng.integers(0, 62))) for _ in range(5)]]))
    nodes = spark.createDataFrame([(i, int(f), 10) for i, f in enumerate(fps)], "node bigint, fp bigint, size int")
    for bits in (0, 1, 2, 5):
        edges = [(r.a, r.b) for r in simhash.links(nodes, bits, crowd=crowd).collect()]
        label = np.arange(len(fps))
        for _ in range(len(fps)):
            for a, b in edges:
                label[a] = label[b] = min(label[a], label[b])
        assert label.tolist() == _components(fps.view(np.uint64), bits).tolist(), bits
    n, both = simhash.bit_statistics(nodes)
    p = simhash.plan(n, both, 5)
    assert sum(t + 1 for t in p.thresholds) == 6 and sum(p.masks) == 2**64 - 1


def test_simhash_digest(spark):
    import xxhash

    got = {r.doc_id: r for r in simhash.digest(table(spark)).collect()}
    for i, t in enumerate(TEXTS):
        w = (t or "").encode().lower().split()
        h = [xxhash.xxh64_intdigest(b" ".join(w[j : j + 3]), 42) for j in range(max(1, len(w) - 2))] if w else []
        want = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
        assert got[i].fingerprint == f"{want:016x}"
    assert got[5].component_id == 3 and got[2].component_id == 0
    kept = sorted(r.doc_id for r in simhash.keep_one(table(spark)).collect())
    assert 5 not in kept and 3 in kept and 1 not in kept


def _kept(texts, shingle=5, similarity=0.8):
    """Positions that stay: the first of each chain of texts with similar sets of word shingles."""
    words = [(t or "").encode().lower().split() for t in texts]
    sets = [{tuple(w[i : i + shingle]) for i in range(max(1, len(w) - shingle + 1))} if w else set() for w in words]
    label, pairs = list(range(len(texts))), 0
    for j, y in enumerate(sets):
        for i, x in enumerate(sets[:j]):
            if len(x & y) >= similarity * len(x | y) - 1e-9:
                pairs += 1
                old, new = max(label[i], label[j]), min(label[i], label[j])
                label = [new if v == old else v for v in label]
    return sorted(set(label)), pairs


def test_no_similar_pair_is_missed(spark):
    rng = np.random.default_rng(7)
    texts = [None, "", "  ", "one two", "one two", "one two three", *TEXTS[3:9]]
    for k in range(60):  # edits of short texts, close to a similarity of 0.8 from both sides
        words = [f"v{x}" for x in rng.integers(0, 900, int(rng.integers(20, 120)))]
        for _ in range(2):
            copy = list(words)
            for at in rng.choice(len(words), int(rng.integers(1, 1 + max(1, len(words) // 40))), replace=False):
                copy[at] = f"new{rng.integers(0, 10**6)}"
            texts += [" ".join(copy)]
        texts += [" ".join(words)]
    texts += [f"{PASSAGE} {' '.join(f'u{i}y{j}' for j in range(12))}" for i in range(70)]  # one passage in many texts that differ
    want, _ = _kept(texts)
    assert sorted(r.doc_id for r in simhash.keep_one(table(spark, texts)).collect()) == want


def test_pairs_looked_at_follow_the_texts(spark, monkeypatch):
    """Copies with edits of their own: in one group with the text they come from, or too far from it and from each other."""
    rng = np.random.default_rng(11)
    texts, words = [], [f"b{i}" for i in range(200)]
    for k in range(90):
        copy = list(words)
        for at in rng.choice(200, 5 if k % 3 else 9, replace=False):  # a similarity of 0.78 and less, or of 0.6
            copy[at] = f"edit{k}x{at}"
        texts.append(" ".join(copy))
    for texts in (texts, [*texts, " ".join(words)]):  # without and with the text they come from
        want, pairs = _kept(texts)
        asked, similar = [], simhash.similar
        with monkeypatch.context() as m:
            m.setattr(simhash, "similar", lambda p, *a, **k: asked.append(p.count()) or similar(p, *a, **k))
            assert sorted(r.doc_id for r in simhash.keep_one(table(spark, texts)).collect()) == want
        assert sum(asked) <= 5 * len(texts), (asked, pairs, len(want))


def test_packing(spark):
    rng = np.random.default_rng(4)
    sizes = sorted(rng.integers(1, 100, 200).tolist(), reverse=True)
    sources, clusters = [f"s{x}" if x else None for x in rng.integers(0, 6, 200)], rng.integers(0, 60, 200).tolist()
    assert packing.best_fit(sizes, sources, clusters, 100) == packing.brute_force(sizes, sources, clusters, 100)
    out = packing.digest(docs(spark)).toPandas()
    words = {r.doc_id: len(r.text.encode().split()) for r in docs(spark).collect()}
    assert out.groupby("doc_id").n_tokens.sum().to_dict() == words
    assert (out.dropna().groupby(["shard", "bin"]).n_tokens.sum() <= packing.CAPACITY).all()
    # one shard: the whole query against looking at every bin
    rows = packing.measure(docs(spark), near=True).toPandas()
    pieces = [(min(packing.CAPACITY, n - at), d, at // packing.CAPACITY, s, c) for d, s, c, n in zip(rows.doc_id, rows.source, rows.cluster, rows.n_tokens) for at in range(0, n, packing.CAPACITY)]
    pieces.sort(key=lambda p: (-p[0], p[1], p[2]))
    want = packing.brute_force([p[0] for p in pieces], [p[3] for p in pieces], [p[4] for p in pieces], packing.CAPACITY)
    assert out.shard.max() == 0 and {(p[1], p[2]): b for p, b in zip(pieces, want)} == {(r.doc_id, r.piece): r.bin for r in out.dropna().itertuples()}
    comp = {r.doc_id: r.component_id for r in simhash.near_components(docs(spark), shingle=5).collect()}
    by = rows.groupby("cluster").doc_id.apply(set)
    assert sorted(map(sorted, by)) == sorted(sorted(d for d in comp if comp[d] == c) for c in set(comp.values()))
    for _, own in out.dropna().merge(rows[["doc_id", "source", "cluster"]], on="doc_id").groupby(["shard", "bin"]):
        assert own.source.dropna().is_unique and own.cluster.is_unique
    t = packing.pack(packing.measure(table(spark))).toPandas()
    assert t[t.doc_id < 3].bin.isna().all() and packing.digest(table(spark, [])).count() == 0


def test_sequences(spark):
    rows = docs(spark).where("doc_id < 40")
    tokens = token_table.write_token_table(rows, token_table.new_path(spark, "tokens"))
    placed = packing.pack(packing.token_items(tokens, rows), capacity=512)
    ids = {r.doc_id: list(r.ids) for r in tokens.collect()}
    got = {(r.shard, r.bin): r for r in packing.build_sequences(placed, tokens).collect()}
    assert sum(r.n_tokens for r in got.values()) == sum(map(len, ids.values())) and all(len(r.ids) == r.n_tokens <= 512 for r in got.values())
    for key, r in got.items():
        own = sorted((p for p in placed.where(f"shard = {key[0]} AND bin = {key[1]}").collect()), key=lambda p: (-p.n_tokens, p.doc_id, p.piece))[:3] if key[1] < 3 else []
        if own:
            assert list(r.ids)[: own[0].n_tokens] == ids[own[0].doc_id][own[0].start : own[0].start + own[0].n_tokens] and r.doc_ids[0] == own[0].doc_id


def test_hot_keys_are_joined_apart(spark, monkeypatch):
    from fairsummary.llm import common

    rows = common.materialize(spark.range(100).selectExpr("id", "CASE WHEN id < 60 THEN 1 ELSE id END AS k"), "rows")
    label = common.materialize(rows.groupBy("k").agg(F.count("*").alias("n")).selectExpr("k", "k * 2 AS twice", "n"), "label")
    want = sorted((r.id, r.k * 2) for r in rows.collect())
    assert sorted((r.id, r.twice) for r in common.label_rows(rows, label, "k").collect()) == want
    monkeypatch.setattr(common, "BROADCAST_BYTES", 0)
    assert sorted((r.id, r.twice) for r in common.label_rows(rows, label, "k", hot=10).collect()) == want


def test_awkward_tables(spark):
    """No rows, repeated and null ids, columns that clash: every operator gives its stated result."""
    none, rows = table(spark, []), [(1, "a b c", "en", "s", 5), (1, "a b c", "en", "s", 5), (None, "x y", None, None, None), (2, None, "en", "s", 0)]
    odd = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").withColumns({c: F.lit("clash") for c in ("ids", "n_bytes", "media", "fp", "score", "kept_text", "spans", "n_tokens", "cluster")})
    labels = spark.createDataFrame([(1, 0, 1), (1, 0, 0), (None, 0, 1)], "doc_id bigint, quality int, toxic int")
    runs = {"op1": substring.digest, "op2": media.digest, "op3": token_table.digest, "op4": packing.digest, "op5": piece_counts.digest, "op6": personal.digest, "op7": lambda d: toxicity.digest(d, labels), "op8": lattice.digest, "op10": simhash.digest}
    for name, run in runs.items():
        assert run(none).count() == 0, name
        got = run(odd).collect()
        assert sorted((r.doc_id is None, r.doc_id or 0) for r in got) == [(False, 1), (False, 1), (False, 2), (True, 0)], name


def test_memory_forgets_only_what_passes():
    m = Memory(lambda ws: [len(w) for w in ws], limit=2)
    assert m({"a", "bb"})["bb"] == 2 and m({"ccc"})["ccc"] == 3
    assert m({"a"}) == {"a": 1, "bb": 2}
