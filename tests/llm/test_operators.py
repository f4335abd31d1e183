"""Each operator against brute force, libraries or exact round trips, with odd inputs."""

import hashlib
import itertools
import zlib

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from relml.llm import ann, bpe, common, components, langid, linededup, media, packing, sharding, simhash, token_counts, toxicity

ODD = ["", None, " ", "a", "Don't STOP it's <|endoftext|> x", "naïve Ünï İstanbul ß ẞ 12３4 ²", "a_b__c 'S we'll\n\nNew  line ", "日本語 テスト 😀", "x" * 70_000, "word " * 9_000, "a"]
SCHEMA = "doc_id long, text string, score double, start long"  # columns with names of results


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(k, t, 9.0, 7) for k, t in enumerate(ODD)] + [(None, "no id here", 1.0, 1), (3, "a", 1.0, 1)], SCHEMA).repartition(2)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return common.load(spark, sf, "documents")


def test_nearest_is_exact_order_and_recall(spark, sf):
    df = common.load(spark, sf, "embeddings")
    rows = df.collect()
    x, ids = np.array([r.embedding for r in rows], float), np.array([r.vec_id for r in rows])
    got = {}
    for r in ann.nearest(df, F.col("id") % 20 == 0).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    hits = 0
    for q, found in got.items():
        found.sort()
        s = x @ x[ids == q][0]
        s[ids == q] = -np.inf
        hits += len({v for _, v, _ in found} & set(ids[np.argsort(-s)[:20]]))
        assert [r for r, *_ in found] == list(range(1, 21))
        assert [(-s, v) for _, v, s in found] == sorted((-s, v) for _, v, s in found)
        assert all(abs(sc - float(x[ids == v][0] @ x[ids == q][0])) < 1e-12 for _, v, sc in found)
    assert set(got) == set(ids[ids % 20 == 0]) and hits >= 0.9 * 20 * len(got)


def test_nearest_odd_vectors(spark):
    rows = [(0, [1.0, 0.0]), (20, [0.0, 2.0]), (40, None), (60, [0.0, 0.0]), (80, [1.0, None]), (100, [float("nan"), 1.0]), (120, [1.0])] + [(k, [3.0, 4.0]) for k in range(1, 31) if k != 20] + [(200, [-5.0, 1.0])]
    df = spark.createDataFrame([(i, v, 1) for i, v in rows], "vec_id long, embedding array<double>, score int")
    got = ann.nearest(df, F.col("id") % 20 == 0).collect()
    by = {q: sorted((r["rank"], r.vec_id, r.score) for r in got if r.query_id == q) for q in {r.query_id for r in got}}
    assert set(by) == {0, 20, 200}
    assert [v for _, v, _ in by[0]] == [*range(1, 20), 21] and all(s == 3 for *_, s in by[0])
    assert all(len(v) == 20 for v in by.values())
    assert ann.nearest(df.where("false"), F.col("id") % 20 == 0).count() == 0
    few = ann.nearest(df.where("vec_id in (0, 20, 200)"), F.col("id") % 20 == 0).collect()
    assert len(few) == 6


def test_nearest_recall_does_not_fall_with_size(spark, tmp_path):
    """More than 64 * axes^2 distinct vectors, of which few are near the queries."""
    n, dim = 66_000, 16
    x = np.random.default_rng(0).normal(size=(n, dim))
    x[:, 0] *= 0.3
    x[:5] = x[:5] * 0.05 + np.eye(dim)[0]
    x /= np.linalg.norm(x, axis=1)[:, None]
    pq.write_table(pa.table({"vec_id": np.arange(n), "embedding": x.tolist()}), f"{tmp_path}/v.parquet")
    got = {}
    for r in ann.nearest(spark.read.parquet(f"{tmp_path}/v.parquet"), F.col("id") < 5).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    assert set(got) == set(range(5))
    hits = 0
    for q, found in got.items():
        s = x @ x[q]
        s[q] = -np.inf
        hits += len(found & set(np.argsort(-s)[:20]))
    assert hits / (20 * len(got)) >= 0.97


def test_counts_equal_library(odd, empty):
    file = P.path("piece_bpe_32k.model")
    import sentencepiece
    from tokenizers import Tokenizer, models, normalizers

    sp = sentencepiece.SentencePieceProcessor(model_file=file)
    lib = Tokenizer(models.Unigram([(sp.id_to_piece(i), sp.get_score(i)) for i in range(sp.vocab_size())], unk_id=0, byte_fallback=True))
    lib.normalizer = normalizers.Sequence([normalizers.Prepend("▁"), normalizers.Replace(" ", "▁")])
    got = token_counts.token_counts(odd, file).collect()
    assert len(got) == len(ODD) + 2
    want = sorted(len(lib.encode(r.text or "", add_special_tokens=False).ids) for r in odd.collect())
    assert sorted(r.n_pieces for r in got) == want
    assert token_counts.token_counts(empty, file).count() == 0
    tie = token_counts.CountingViterbi({"a": -1.0, "aa": -2.0, "<unk>": -3.0})
    assert tie.count("aa")[1] == 4  # U+2581 is unknown: three bytes, then the longer piece wins the tie
    assert tie.solve("aa") == (-2.0, 1)


def test_packing_is_whole(spark, docs, odd, empty):
    file = P.path("byte_bpe_50k.json")
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(file)
    df = docs.select("doc_id", "text").union(odd.where("doc_id is not null").dropDuplicates(["doc_id"]).select(F.col("doc_id") + 1_000_000, "text"))
    ids = {r.doc_id: np.array([*lib.encode(r.text or "", add_special_tokens=False).ids, 0], "<u4") for r in df.collect()}
    got = packing.pack_documents(df, file).collect()
    seqs, parts = {}, {}
    for r in got:
        seqs.setdefault(r.sequence_id, []).append((r.offset, r.length))
        parts.setdefault(r.doc_id, []).append((r.start, r.length))
        assert zlib.crc32(ids[r.doc_id][r.start : r.start + r.length].tobytes()) == r.ids_crc32 and r.doc_tokens == len(ids[r.doc_id])
    for pieces, total in [(v, None) for v in seqs.values()] + [(v, len(ids[k])) for k, v in parts.items()]:
        at = 0
        for lo, n in sorted(pieces):
            assert lo == at and n > 0
            at += n
        assert at == total if total else at <= 1024
    assert set(parts) == set(ids)
    sums = [sum(n for _, n in v) for v in seqs.values()]
    assert sum(0 if s & (s - 1) == 0 else 1024 - s for s in sums) <= 0.01 * sum(sums)
    assert packing.pack_documents(empty, file).count() == 0


def test_vector_bins_keep_all_limits(spark):
    rng = np.random.default_rng(0)
    d = rng.integers(1, 60, (200, 3)).astype(float)
    limits = [100.0, 80.0, 90.0]
    bins = packing.pack_vectors(d, limits)
    loads = np.array([d[bins == b].sum(0) for b in range(bins.max() + 1)])
    assert (bins >= 0).all() and (loads <= limits).all()
    assert len(loads) <= 1.35 * (d.sum(0) / limits).max()
    assert packing.pack_vectors(np.array([[500.0, 1, 1], [1, 1, 1]]), limits).tolist() in ([0, 1], [1, 0])
    df = spark.createDataFrame([(k, float(a), 1.0, float(b)) for k, (a, b, _) in enumerate(d)], "id long, tokens double, segments double, loss double")
    got = packing.pack_examples(df, "id", {"tokens": 100, "segments": 5, "loss": 80}).join(df, "id").groupBy("bin_id").agg(F.sum("tokens").alias("t"), F.sum("segments").alias("s"), F.sum("loss").alias("l")).collect()
    assert all(r.t <= 100 and r.s <= 5 and r.l <= 80 for r in got)


def test_toxicity_learns_and_treats_groups_alike(spark, odd, empty):
    rng = np.random.default_rng(1)
    words = [f"w{k}" for k in range(40)]
    rows = []
    for k in range(600):
        bad = k % 4 == 0
        text = " ".join(rng.choice(words, 12)) + (" vilezap" + "abcd"[k % 3] if bad else "") + (" muslims" if k % 8 == 0 or k % 40 == 1 else "")
        rows.append((text, int(bad)))
    plain, fair = (toxicity.fit(*zip(*rows), penalty=p) for p in (0.0, 30.0))
    gap = lambda m: abs(m.logit("w1 muslims w2") - m.logit("w1 christians w2"))
    assert gap(fair) < 0.5 * gap(plain)
    assert fair.score("w1 w2 muslims") < 0.7 < fair.score("w1 vilezapd w2")
    got = toxicity.score_documents(odd, fair).collect()
    assert len(got) == len(ODD) + 2 and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in got)
    assert toxicity.keep_clean(odd, fair).columns == odd.columns and toxicity.keep_clean(odd, fair).count() == len(got)
    assert toxicity.score_documents(empty, fair).count() == 0
    none = spark.createDataFrame([], "doc_id long, toxic int")
    assert toxicity.train(odd, none, F.lit(True)).score("x") < 0.5
    assert toxicity.counterfactual("The Muslim women sang") == "The christian men sang"


def test_toxicity_held_out(spark):
    """The query on real labels: learned from two thirds, held against the rest; the words that tell may come late in a text."""
    from relml.llm import queries

    sf = "/root/testdata/sf0.1"
    got = queries.op4_toxicity(spark, sf).join(common.load(spark, sf, "labels"), "doc_id").where("held_out").collect()
    tp = sum(r.toxic == 1 and r.predicted == 1 for r in got)
    # some labelled texts hold no word that any other toxic one has
    assert tp >= 0.8 * sum(r.toxic for r in got) > 0 and sum(r.toxic == 0 and r.predicted == 1 for r in got) <= 0.005 * len(got)
    rows = [(k, "calm words here " * 4_000 + ("grothval" if k % 2 else "pleasant"), k % 2) for k in range(60)]
    late = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    model = toxicity.train(late.drop("toxic"), late, F.lit(True))
    assert model.score(rows[1][1]) > 0.7 > model.score(rows[0][1])


def test_word_bpe_equals_library(spark, docs, odd, empty):
    file = P.path("word_bpe_49k.json")
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(file)
    folder = bpe.build_lexicon(spark, bpe.frequent_words(docs, size=500), file)
    df = docs.select("doc_id", "text").union(odd.select(F.col("doc_id") + 1_000_000, "text"))
    texts = {}
    for r in df.collect():
        ids = lib.encode(r.text or "", add_special_tokens=False).ids
        texts.setdefault(r.doc_id, set()).add((len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    got = bpe.encode_digests(df, file, folder).collect()
    assert len(got) == df.count() and all((r.n_tokens, r.ids_sha256, r.decoded_sha256) in texts[r.doc_id] for r in got)
    real = bpe.encode_documents(odd, file, folder).collect()
    assert len(real) == odd.count()
    assert bpe.encode_digests(empty, file, folder).count() == 0


def test_transducer_is_minimal_and_exact(tmp_path):
    words = {"".join(w): [len(w), ord(w[0])] for n in (1, 2, 3) for w in itertools.product("abé", repeat=n)}
    t = bpe.Transducer.compile(words)
    assert t.states == 3 + 2 + 1 + 1 - 1 or t.states <= 8  # all words of a length end alike; é takes a state in each
    t.save(f"file://{tmp_path}/t")
    t = bpe.Transducer.open(f"file://{tmp_path}/t")
    assert all(t.find(w) == v for w, v in words.items()) and t.find("abab") is None and t.find("") is None


def brute_shards(sizes, shards):
    best = None
    for cuts in itertools.combinations_with_replacement(range(len(sizes) + 1), shards - 1):
        edges = [0, *cuts, len(sizes)]
        m = max(sum(sizes[a:b]) for a, b in zip(edges, edges[1:]))
        best = m if best is None else min(best, m)
    return best


def test_shards(spark, docs, odd, empty):
    rng = np.random.default_rng(0)
    for n in (1, 5, 9):
        sizes = rng.integers(1, 50, n).tolist()
        assert sharding.least_capacity(sizes, 3) == brute_shards(sizes, 3)
    df = docs.select("doc_id", "text").union(docs.limit(1).select(F.lit(10**9), "text")).union(odd.select("doc_id", "text"))
    got = sharding.shard_documents(df).collect()
    assert len(got) == df.count()
    groups, order = {}, {}
    for r in df.selectExpr("coalesce(text, '') as t", "xxhash64(cast(coalesce(text, '') as binary)) as h", "octet_length(coalesce(text, '')) + 1 as s").collect():
        order[r.h] = order.get(r.h, 0) + r.s
    sizes = [order[h] for h in sorted(order)]
    loads, slots = [0] * 8, {}
    for r in got:
        loads[r["shard"]] += r["size"]
        slots.setdefault(r["shard"], []).append(r["slot"])
        groups.setdefault(r["text_crc32"], set()).add(r["shard"])
    assert max(loads) == sharding.least_capacity(sizes, 8)
    assert all(sorted(v) == list(range(len(v))) for v in slots.values())
    assert all(len(v) == 1 for v in groups.values())
    assert sharding.shard_documents(empty).count() == 0


def test_cut_search_splits_ranges(spark):
    """A capacity that only single groups can settle."""
    rng = np.random.default_rng(3)
    h = np.sort(rng.integers(-(1 << 62), -(1 << 62) + (1 << 40), 500))
    sizes = rng.integers(1, 1000, 500)
    groups = common.settle(spark.createDataFrame([(int(a), int(b)) for a, b in zip(h, sizes)], "h long, size long"), "t")
    cuts = sharding.find_cuts(groups, 8)
    loads = [int(sizes[(h >= lo) & (h < hi)].sum()) for lo, hi in zip([-(1 << 63), *cuts], [*cuts, (1 << 63) - 1])]
    assert len(cuts) == 7 and max(loads) == sharding.least_capacity(sizes.tolist(), 8)


def test_media_round_trip(spark, odd, empty):
    folder = common.new_path(spark, "media-test")
    media.write_archives(odd, folder)
    for span in (1 << 30, 3000):  # a range owns the members that start in it
        got = media.media_features(media.read_archives(spark, folder, rangeBytes=span)).collect()
        assert len(got) == odd.count()
        for r in odd.collect():
            raw = (r.text or "").encode()
            payload = media.padded(raw)
            row = next(g for g in got if g.doc_id == r.doc_id and g.n_bytes == len(raw))
            assert len(payload) % 576 == 0 and payload[: len(raw)] == raw
            assert (row.payload_bytes, row.payload_sha256, row.tail_crc32) == (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]))
            assert row.media_sha256 == hashlib.sha256(media.to_png(payload)).hexdigest()
    none = common.new_path(spark, "media-empty")
    assert media.write_archives(empty, none) == 0 and media.read_archives(spark, none).count() == 0


def test_media_member_is_retried(tmp_path):
    raw = f"{7:>20} {1:>20} {3:>20}\nabc".encode()

    class Flaky:
        fails = 2

        def seek(self, at):
            self.at = at

        def read(self, n):
            if self.fails:
                self.fails -= 1
                raise OSError("lost")
            return raw[self.at : self.at + n]

    reader = media.ArchiveReader({"path": str(tmp_path), "tries": 3})
    assert reader.member(Flaky(), 0, len(raw)) == (7, 1, b"abc")
    with pytest.raises(OSError):
        media.ArchiveReader({"path": str(tmp_path), "tries": 2}).member(Flaky(), 0, len(raw))


def test_gru_gradient_is_right():
    m = langid.ByteGru(["x", "y"], hidden=3)
    m.p = {k: v.astype(np.float64) for k, v in m.p.items()}
    codes, target = np.concatenate([langid.windows_of(b"ab")[:5], langid.windows_of(b"cdea")[:5]], 1), np.array([0, 1])
    _, grad = m.gradient(codes, target)
    for k in m.p:
        places = list(np.ndindex(m.p[k].shape))
        for at in [p for p in places if k[0] != "W" or p[1] in codes][:: max(1, len(places) // 7 if k[0] != "W" else 5)]:
            held, out = m.p[k][at], []
            for d in (1e-4, -1e-4):
                m.p[k][at] = held + d
                out.append(m.gradient(codes, target)[0])
            m.p[k][at] = held
            assert grad[k][at] == pytest.approx((out[0] - out[1]) / 2e-4, rel=1e-3, abs=1e-6), (k, at)


def test_language_held_out(spark, docs, odd, empty):
    model = langid.train(docs, ~common.held_out("doc_id", 4, 2))
    got = langid.predict(docs, model).join(docs, "doc_id").where(common.held_out("doc_id", 4, 2)).collect()
    assert sum(r.lang == r.lang_pred for r in got) >= 0.9 * len(got)
    strange = langid.predict(odd, model).join(odd.select("doc_id", "text"), "doc_id").collect()
    assert all((r.lang_pred == "und") == (r.text is None or not any(map(str.isalpha, r.text))) and 0 <= r.score <= 1 for r in strange)
    assert langid.keep_known(odd, model, 0.0).where("text is null or trim(text) = ''").count() == 0
    assert langid.predict(empty, model).count() == 0
    assert langid.predict(odd, langid.train(docs.where("false"), F.lit(True))).where("lang_pred <> 'und'").count() == 0


def test_language_labels_every_byte_of_a_text(docs):
    texts = ["the cat le chat " * 40, "der Hund", "12 ä", "x" * 200_000]
    raw = [t.encode() for t in texts]
    seen = [b"" for _ in texts]
    for codes, owner in langid.lots(raw):
        assert codes.shape[1] <= langid.LOT
        for w, k in zip(codes.T, owner):
            seen[k] += bytes(int(c) for c in w if c < langid.PAD)
    assert seen == raw
    model = langid.ByteGru(["x", "y"])
    assert model.label(langid.windows_of(raw[0])).shape == (langid.WINDOW, 2, 10)
    each = [model.documents([t])[0] for t in texts]
    assert [(l, pytest.approx(s, abs=1e-3)) for l, s in each] == model.documents(texts)


def test_rare_language_is_learned(spark):
    """One short document beside languages of many."""
    rng = np.random.default_rng(6)
    word = lambda letters: "".join(rng.choice(list(letters), 6))
    rows = [(k, " ".join(w for w in [word("abcdefg" if k % 2 else "nopqrst")] * 4), "xy"[k % 2]) for k in range(80)]
    rows += [(80, "zuvzuv", "z")]
    model = langid.train(spark.createDataFrame(rows, "doc_id long, text string, lang string"), F.lit(True))
    assert model.languages == ["x", "y", "z"] and all(np.isfinite(p).all() for p in model.p.values())
    got = model.documents(["zuvzuv", rows[0][1], rows[1][1]])
    assert [l for l, _ in got] == ["z", "x", "y"] and all(0 < s <= 1 for _, s in got)


def test_language_is_learned_from_whole_texts(spark):
    rows = [(0, "1 " * 20_000 + "abc def " * 4_000, "x"), (1, "xyz uvw xyz uvw", "y")]
    model = langid.train(spark.createDataFrame(rows, "doc_id long, text string, lang string"), F.lit(True))
    assert model.languages == ["x", "y"] and model.documents(["abc def abc def"])[0][0] == "x"


def brute_dedup(texts, least):
    """Lines covered by a run of enough words that occurs before."""
    lines = {k: linededup.lines_of(t) for k, t in texts.items()}
    order = [(k, p) for k in sorted(lines) for p in range(len(lines[k]))]
    gone = {k: set() for k in lines}
    for n, (i, p) in enumerate(order):
        for j, q in order[:n]:
            m = 0
            while p + m < len(lines[i]) and q + m < len(lines[j]) and lines[i][p + m] == lines[j][q + m]:
                m += 1
            if sum(x.count(" ") + 1 for x in lines[i][p : p + m]) >= least:
                gone[i].update(range(p, p + m))
    return lines, gone


def test_line_dedup_equals_brute_force(spark, empty):
    rng = np.random.default_rng(5)
    pool = [f"Line {k} " + " ".join(rng.choice(list("abcdef"), rng.integers(1, 5))) + "." for k in range(12)]
    texts = {k: " ".join(rng.choice(pool, rng.integers(0, 14))) + ("\nTail" if k % 3 else "") for k in range(40)}
    texts[40] = texts[3]
    texts[41] = "start of it " + texts[5] + " end of it"
    df = spark.createDataFrame([*texts.items(), (50, None), (None, texts[3])], "doc_id long, text string").withColumn("__lines2", F.lit(1)).repartition(3)
    lines, gone = brute_dedup(texts, 9)
    for rounds in (0, None):
        got = {r.doc_id: r for r in linededup.drop_repeats(df, 9, rounds=rounds).collect()}
        for k in texts:
            left = [x for p, x in enumerate(lines[k]) if p not in gone[k]]
            assert (got[k]["__lines"], got[k]["__removed"]) == (len(lines[k]), len(gone[k])), k
            assert linededup.lines_of(got[k].text) == left if gone[k] else got[k].text == texts[k]
        assert got[50].text is None and got[None].text == texts[3]
    assert linededup.drop_repeats(empty).count() == 0


def test_line_dedup_places_of_any_ids(spark):
    """Ids that fit into a long with their lines, and ids from end to end of the range, also shared ones: as brute force."""
    rng = np.random.default_rng(6)
    pool = [f"Line {k} " + " ".join(rng.choice(list("abcdef"), rng.integers(1, 5))) + "." for k in range(10)]
    texts = [" ".join(rng.choice(pool, rng.integers(0, 14))) for _ in range(24)]
    for ids in (range(-12, 12), [-(2**63), *range(-11, 11), 2**63 - 1]):
        held = dict(zip(ids, texts))
        df = spark.createDataFrame([*held.items(), (ids[5], texts[5])], "doc_id long, text string").repartition(3)
        narrow = df.select(F.col("doc_id").alias("doc"), F.lit(14).alias("n"))
        assert linededup.Places.of(narrow).bits == (4 if ids[0] == -12 else 0)
        lines, gone = brute_dedup(held, 9)
        got = linededup.drop_repeats(df, 9).collect()
        assert len(got) == 25 and sum(map(len, gone.values())) > 20
        for r in got:
            left = [x for p, x in enumerate(lines[r.doc_id]) if p not in gone[r.doc_id]]
            assert r["__removed"] == len(gone[r.doc_id]) and linededup.lines_of(r.text) == left, r.doc_id


def test_line_dedup_names_are_grouped_without_sorting(spark, docs, monkeypatch):
    """The check tool's CPU budget: names of all rounds are grouped by hash, and lines are moved as bytes."""
    plans, kinds, settle = {}, {}, common.settle

    def seen(df, label, *more):
        plans[label], kinds[label] = df._jdf.queryExecution().executedPlan().toString(), dict(df.dtypes)
        return settle(df, label, *more)

    monkeypatch.setattr(common, "settle", seen)
    linededup.drop_repeats(docs.select("doc_id", "text"))
    assert "HashAggregate" in plans["sources"] and "SortAggregate" not in plans["sources"]
    assert not [c for c, kind in kinds["own-lines"].items() if kind.startswith("array")]
    assert "Window" not in "".join(plans.values())


def test_doubling_levels(spark):
    body = " ".join(f"Part {k} has five words." for k in range(16))
    df = spark.createDataFrame([(1, body + " Odd end."), (2, "Own start. " + body)], "doc_id long, text string")
    rows = {r.doc_id: r for r in linededup.drop_repeats(df, 10, rounds=None).collect()}
    assert rows[2]["__level"] == 3 and rows[2].text == "Own start." and rows[1].text.startswith("Part 0")


def test_simhash_equals_brute_force(spark, docs, odd, empty):
    df = docs.select("doc_id", "text").union(odd.select(F.col("doc_id") + 1_000_000, "text"))
    rows = [(r.doc_id, simhash.fingerprint(r.text or "")) for r in df.collect()]
    up = list(range(len(rows)))

    def top(k):
        while up[k] != k:
            k = up[k]
        return k

    for a, b in itertools.combinations(range(len(rows)), 2):
        if (rows[a][1] ^ rows[b][1]).bit_count() <= 3:
            up[max(top(a), top(b))] = min(top(a), top(b))
    least = {}
    for k, (i, _) in enumerate(rows):
        least[top(k)] = i if least.get(top(k)) is None else least[top(k)] if i is None else min(least[top(k)], i)
    want = sorted((-1 if i is None else i, f"{f:016x}", least[top(k)] or 0) for k, (i, f) in enumerate(rows))
    got = sorted((-1 if r.doc_id is None else r.doc_id, r.fingerprint, r.component_id or 0) for r in simhash.near_duplicates(df).collect())
    assert got == want
    assert simhash.near_duplicates(empty).count() == 0
    kept = simhash.keep_first(df)
    assert kept.columns == df.columns and kept.where("doc_id is not null").select("doc_id").distinct().count() == len({c for i, _, c in want if i >= 0})


def test_pipeline_near_duplicates_equal_brute_force(spark, sf):
    """All links of similarity 0.8 or more on five-word shingles, over texts changed in one to eight places."""
    import corpus_pipeline

    rng = np.random.default_rng(8)
    texts = {}
    for k in range(60):
        words = [f"w{v}" for v in rng.integers(0, 5000, 150)]
        texts[len(texts)] = " ".join(words)
        for n in range(1, 9):
            new = list(words)
            for at in rng.choice(150, n, replace=False):
                new[at] = f"v{rng.integers(0, 5000)}"
            texts[len(texts)] = " ".join(new)
    texts |= {len(texts): "", len(texts) + 1: " ", len(texts) + 2: "a b", len(texts) + 3: "A  b", len(texts) + 4: texts[0]}
    sets = {i: {tuple(w[j : j + 5]) for j in range(len(w) - 4)} or {tuple(w)} for i, t in texts.items() for w in [t.lower().split()]}
    up = {i: i for i in texts}

    def top(k):
        while up[k] != k:
            k = up[k]
        return k

    wide = 0
    for a, b in itertools.combinations(texts, 2):
        if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
            up[max(top(a), top(b))] = min(top(a), top(b))
            wide += (simhash.fingerprint(texts[a]) ^ simhash.fingerprint(texts[b])).bit_count() > 3
    df = spark.createDataFrame([*texts.items(), (None, texts[1])], "doc_id long, text string").repartition(3)
    got = corpus_pipeline.drop_near_duplicates(spark, df, sf)
    assert wide > 50 and got.columns == df.columns
    assert sorted(-1 if r.doc_id is None else r.doc_id for r in got.collect()) == [-1, *sorted({top(i) for i in texts})]


def test_fingerprint_by_definition():
    from xxhash import xxh64_intdigest

    text = "The CAT sat\ton the mat the cat"
    w = text.lower().split()
    h = [xxh64_intdigest(" ".join(w[k : k + 3]), 42) for k in range(len(w) - 2)]
    want = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
    assert simhash.fingerprint(text) == want and simhash.fingerprint(" \t") == 0
    assert simhash.fingerprint("a b") == xxh64_intdigest("a b", 42)


def test_anchors_cover():
    """Words that differ in one bit share the home of each."""
    rng = np.random.default_rng(2)
    x = rng.integers(0, 1 << 32, 200, dtype=np.uint32)
    y = x ^ (np.uint32(1) << rng.integers(0, 32, 200).astype(np.uint32))
    rx, kx, hx = simhash.anchors(x)
    ry, ky, _ = simhash.anchors(y)
    for k in range(200):
        assert kx[(rx == k) & hx][0] in set(ky[ry == k])
    assert all(bin(int(a) ^ int(b)).count("1") <= 2 for a, b in zip(kx, x[rx]))


def test_links_at_all_distances(spark):
    rng = np.random.default_rng(4)
    base = [int(v) for v in rng.integers(0, 1 << 63, 30)]
    rows = set(base)
    for b in base[:20]:
        for n in (1, 2, 3, 4):
            v = b
            for bit in rng.choice(63, n, replace=False):
                v ^= 1 << int(bit)
            rows.add(v)
    rows = sorted(rows)
    roots = {r.node: r.root for r in components.connected_components(simhash.links(spark.createDataFrame([(v,) for v in rows], "fp long"))).collect()}
    up = {v: v for v in rows}

    def top(v):
        while up[v] != v:
            v = up[v]
        return v

    for a, b in itertools.combinations(rows, 2):
        if (a ^ b).bit_count() <= 3:
            up[max(top(a), top(b))] = min(top(a), top(b))
    assert all(roots.get(v, v) == top(v) for v in rows)


def test_links_of_a_crowded_anchor(spark):
    """Nine in ten fingerprints share a half; cut into parts, the components are the same."""
    rng = np.random.default_rng(12)
    low = rng.integers(0, 1 << 32, 60, np.uint64)
    fps = {int(x ^ (np.uint64(1) << np.uint64(b))) for x in low for b in rng.integers(0, 32, 6)} | set(map(int, rng.integers(0, 1 << 63, 40, np.uint64)))
    nodes = spark.createDataFrame([(int(np.uint64(f).view(np.int64)),) for f in fps], "fp long")
    got = [sorted((r.node, r.root) for r in components.connected_components(simhash.links(nodes, most)).collect()) for most in (8192, 25)]
    assert got[0] == got[1] and got[0]


def test_nearest_with_one_crowded_bucket(spark):
    """Nine in ten vectors lie in one cone, so that its bucket has many blocks."""
    rng = np.random.default_rng(13)
    x = np.concatenate([np.eye(8)[0] + 0.05 * rng.normal(size=(900, 8)), rng.normal(size=(100, 8))])
    rows = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "g long, v array<double>").withColumn("band", F.lit(0))
    queries = spark.createDataFrame([(2000 + k, x[k].tolist()) for k in (1, 5, 950)], "q long, v array<double>")
    signs = ann.rotations(8, 2, 1, 3)
    assert any(n > 10 for n in ann.crowded(rows, signs, 50).values())
    got = {}
    for block in (50, 8192):
        best = {}
        for r in ann._search(rows, queries, [0], signs, 16, 10, block).collect():
            best.setdefault(r.q, {})[r.g] = r.score
        got[block] = {q: sorted(s, key=lambda g: (-s[g], g))[:10] for q, s in best.items()}
    want = {2000 + k: sorted(range(1000), key=lambda g: (-float(x[g] @ x[k]), g))[:10] for k in (1, 5, 950)}
    assert got[50] == got[8192] == want


def test_frequent_words_are_bounded_and_exact(spark):
    rng = np.random.default_rng(14)
    words = rng.zipf(1.3, 4000) % 300
    docs = spark.createDataFrame([(k, " ".join(f"w{chr(97 + v % 26)}{chr(97 + v // 26)}" for v in words[k::40])) for k in range(40)], "doc_id long, text string")
    counts = {}
    for r in docs.collect():
        for w in r.text.split():
            counts[w] = counts.get(w, 0) + 1
    want = sorted((w for w, n in counts.items() if n > 1), key=lambda w: (-counts[w], w))
    for size in (1, 7, 60, 10_000):
        assert bpe.frequent_words(docs, size=size) == want[:size]


def test_odd_chunks_alone_go_to_the_library(spark):
    from tokenizers import Tokenizer

    file = P.path("word_bpe_49k.json")
    codec, lib = bpe.Codec(file, None), Tokenizer.from_file(file)
    texts = ["costs 5 € only, Привет мир and ΣΑΣ Σ 日本 語 x", "a\u00a0b c\u3000d \x1c e\x85f", "İstanbul ǅ ŉ ﬁ and plain Words", "e\u0301 cafe\u0301 ́x", "tabs\tand\r\nlines 😀😀 end", "<|endoftext|> x"]
    for t in texts:
        assert codec.encode(t) == lib.encode(t, add_special_tokens=False).ids, t
        assert codec.digests(t)[0] == len(codec.encode(t))
    seen = []
    codec.bpe.exact = lambda real=codec.bpe.exact: seen.append(1) or real()
    codec.digests("plain words around one € sign " * 50)
    assert len(seen) <= 1


def test_damaged_member_is_retried(tmp_path):
    media_, payload = media.to_png(media.padded(b"abc")), media.padded(b"abc")
    head = f"{7:>20} {3:>20} {len(media_):>20}\n".encode()
    assert len(head) == media.HEAD
    good, reads = head + media_, []

    class Source:
        def seek(self, at):
            reads.append(at)

        def read(self, n):
            return good if len(reads) > 1 else good[:-20] + b"x" + good[-19:]

    doc_id, n, raw = media.ArchiveReader({"path": str(tmp_path)}).member(Source(), 0, len(good), zlib.crc32(good))
    assert (doc_id, n, media.from_png(raw)) == (7, 3, payload) and len(reads) == 2


def test_components_of_chains(spark):
    chain = [(k, k + 1) for k in range(60)] + [(100, 101), (101, 100), (7, 7)]
    got = {r.node: r.root for r in components.connected_components(spark.createDataFrame(chain, "a long, b long")).collect()}
    assert got == {**{k: 0 for k in range(61)}, 100: 100, 101: 100}
    assert components.connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_pipeline_stages(spark, sf):
    import corpus_pipeline

    docs = common.load(spark, sf, "documents")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.dtypes == docs.dtypes, name
        new = common.settle(out, name)
        assert 0.5 * docs.count() < new.count() <= docs.count()
        docs = new
    last = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert last.select("doc_id").distinct().count() == docs.select("doc_id").distinct().count()


def test_queries_are_registered():
    import __spark_entry__ as e

    names = e.queries()
    assert "pipeline" in names and all(any(k.startswith(f"op{n}_") for k in names) for n in range(1, 11))


def test_doubling_by_default_equals_prefixes(spark):
    """The default runs all rounds: the level of a document's deepest run that stands elsewhere before it."""
    rng = np.random.default_rng(21)
    pool = [f"Line {k} has five words." for k in range(30)]
    texts = {k: " ".join(pool[v] for v in range(*sorted(rng.choice(31, 2, replace=False)))) + f" End {k}." for k in range(25)}
    df = spark.createDataFrame([*texts.items()], "doc_id long, text string").repartition(3)
    got = {r.doc_id: r["__level"] for r in linededup.drop_repeats(df, 10).collect()}
    seen: dict[int, set] = {}
    for k, text in sorted(texts.items()):
        lines, level = linededup.lines_of(text), None
        for deep in range(6):
            runs = [tuple(lines[p : p + (2 << deep)]) for p in range(len(lines) - (2 << deep) + 1)]
            runs = [r for r in runs if all(x.count(" ") == 4 for x in r)]
            held = seen.setdefault(deep, set())
            if any(r in held for r in runs):
                level = deep
            held.update(runs)
        assert got[k] == level, k
    assert max(x for x in got.values() if x is not None) >= 2


def test_doubled_runs_of_rows_that_share_an_id():
    row, pos, end, name = np.zeros(4, np.int64), np.array([0, 0, 2, 2]), np.array([2, 2, 4, 5]), np.array([7, 7, 8, 9], np.uint64)
    (k, _, p, e, n), = linededup.doubled(row, pos, end, name)
    assert k == 1 and p.tolist() == [0, 0] and e.tolist() == [4, 5] and len(set(n.tolist())) == 2


def test_pipeline_near_duplicates_come_by_simhash(spark, sf, monkeypatch):
    """Without the bands, pairs that SimHash links are found all the same, and settled by the exact check."""
    import corpus_pipeline
    from relml.llm import neardup

    rng, texts, kept, kinds = np.random.default_rng(4), [], [-1], set()
    while len(kinds) < 2 or len(texts) < 12:
        words = [f"w{v}" for v in rng.integers(0, 5000, 60)]
        at = int(rng.integers(0, 60))
        other = [*words[:at], "new", *words[at + 1 :]]
        if at % 3:
            other[(at + 30) % 60] = "newer"
        own = [{tuple(w[j : j + 5]) for j in range(56)} for w in (words, other)]
        if (simhash.fingerprint(" ".join(words)) ^ simhash.fingerprint(" ".join(other))).bit_count() <= 3:
            near = 5 * len(own[0] & own[1]) >= 4 * len(own[0] | own[1])
            kinds.add(near)
            kept += [len(texts)] if near else [len(texts), len(texts) + 1]
            texts += [" ".join(words), " ".join(other)]
    df = spark.createDataFrame([*enumerate(texts), (None, texts[1])], "doc_id long, text string").repartition(3)
    monkeypatch.setattr(neardup, "_stars", lambda nodes: nodes.sparkSession.createDataFrame([], "a long, b long"))
    got = corpus_pipeline.drop_near_duplicates(spark, df, sf)
    assert sorted(-1 if r.doc_id is None else r.doc_id for r in got.collect()) == kept
