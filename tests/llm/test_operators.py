"""Document operators against brute force, with nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns."""

import collections
import hashlib
import random
import re
import zlib

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pytest
import tiktoken
from pyspark.sql import functions as F

from incrank.llm import bpe, common, exact, media, neardup, packing, quality, sharding, suffix, tokencounts, toxicity
from incrank.llm.common import column_bytes, texts_of
from incrank.llm.components import connected_components

SF = "/root/testdata/sf0.001"
#: Columns whose names operators use inside.
CLASH = "text string, doc_id bigint, digest string, keep_id int, token int, part int, block string, blocks string, bands int, rank int, shard int, cell int, place int, length int, draw int, verdicts int, n_chars bigint"
LONG = " ".join(f"word{k % 977}x{k % 31}" for k in range(60_000))


def table(spark, rows, clash=True):
    """Rows of (doc_id, text), with columns that clash."""
    if not clash:
        return spark.createDataFrame(rows, "doc_id bigint, text string")
    return spark.createDataFrame([(t, i, "d", 1, 2, 3, "b", "c", 4, 5, 6, 7, 8, 9, 10, 11, None if t is None else len(t)) for i, t in rows], CLASH)


@pytest.fixture(scope="module")
def edge_rows():
    p = "the quick brown fox jumps over the lazy dog while seven wizards box quietly"
    return [(1, None), (2, ""), (3, "  \n\t "), (4, "A"), (5, p), (5, p), (6, p.upper()), (7, f"zz {p} yy"), (8, "Ünïcödé ÄÖ 中文 🙂"), (None, "no id here"), (None, None), (9, "a" * 5000), (10, LONG), (11, LONG + " end"), (12, "ünïcödé äÖ 中文 🙂")]


EMPTY = []


def outputs(spark, rows):
    """Every operator over the same rows."""
    docs, labels = table(spark, rows), spark.createDataFrame([(4, 1, 0), (5, 0, 1), (None, None, None)], "doc_id bigint, quality int, toxic int")
    spec = bpe.tokenizer_json({bytes([k]): k for k in range(256)} | {b"th": 256, b"the": 257})
    return {
        "media": media.media_round_trip(docs), "packing": packing.best_fit_packing(docs, P.path("word_bpe_49k.json")), "exact": exact.exact_dedup(docs), "bpe": bpe.round_trip(docs, spec, P.PATTERN),
        "quality": quality.importance_resample(docs, labels), "shards": sharding.shuffled_shards(docs), "near": neardup.near_duplicates(docs), "toxicity": toxicity.score_documents(docs, labels),
        "counts": tokencounts.edited_counts(docs, P.path("byte_bpe_50k.json"), P.PATTERN), "suffix": suffix.repeat_digests(docs), "stripped": suffix.remove_repeats(docs),
        "kept": exact.keep_last_copies(docs), "heads": neardup.keep_class_heads(docs), "clean": toxicity.keep_clean(docs, toxicity.fit(docs, labels, toxicity.may_learn)), "no_repeats": suffix.strip_repeats(docs),
    }


def test_empty_tables(spark):
    for name, df in outputs(spark, EMPTY).items():
        assert df.count() == 0, name


def test_edge_rows(spark, edge_rows):
    got = {k: df.toPandas() for k, df in outputs(spark, edge_rows).items()}
    n = len(edge_rows)
    for name in ("media", "exact", "bpe", "quality", "shards", "near", "toxicity", "counts", "suffix", "stripped", "clean", "no_repeats"):
        assert len(got[name]) == n, name
    assert sorted(got["shards"].groupby("shard").size()) == [0] * 0 + sorted([1] * n)[: len(got["shards"].shard.unique())]
    e = got["exact"].set_index("doc_id")
    assert set(e.loc[5].keep_id) == {6} and not e.loc[5].kept.any() and e.loc[6].kept and e.loc[6].group_size == 3
    assert e.loc[2].group_size == 3 and e.loc[2].keep_id == 2  # two nulls and an empty text
    assert e.loc[8].group_size == 1  # only A-Z is lowered
    kept = got["kept"]
    assert sorted(kept.doc_id.dropna()) == [2, 3, 4, 6, 7, 8, 9, 10, 11, 12] and kept.doc_id.isna().sum() == 1
    near = got["near"].dropna(subset=["doc_id"]).drop_duplicates("doc_id").set_index("doc_id")
    assert near.loc[6].class_id == 5 and near.loc[11].class_id == 10 and near.loc[2].class_id == 1 and near.loc[3].class_id == 3
    assert got["near"].class_id.isna().sum() == 2
    heads = got["heads"]
    assert (heads.doc_id == 5).sum() == 1 and 6 not in set(heads.doc_id)
    assert got["toxicity"].score.between(0, 1).all() and got["clean"].columns.tolist() == [c.split()[0] for c in CLASH.split(", ")]
    stripped = got["no_repeats"]
    row = stripped[stripped.doc_id == 7].iloc[0]
    assert row.text == "zz  yy" and row.n_chars == 6 and stripped[stripped.doc_id == 1].iloc[0].text is None
    packed = got["packing"]
    assert packed.groupby("sequence_id").length.sum().max() <= 2048 and len(packed[packed.doc_id == 1]) == 1 and packed[packed.doc_id == 1].iloc[0].length == 1


# 1. Media


@pytest.mark.parametrize("order", "<>")
@pytest.mark.parametrize("tile", [None, (32, 16)])
@pytest.mark.parametrize("compression", [media.RAW, media.PACKBITS, media.LZW, media.DEFLATE])
@pytest.mark.parametrize("dtype,predictor", [("u1", 1), ("u1", 2), ("u2", 2), ("u4", 2), ("f4", 1), ("f4", 3)])
def test_tiff_round_trips(order, tile, compression, dtype, predictor):
    r = np.random.default_rng(1)
    pages = [(r.normal(size=(37, 45, 3)) * 50).astype("f4") if dtype == "f4" else r.integers(0, 4, (h, 45, s)).astype(dtype) for h, s in ((37, 3), (1, 1), (70, 1))]
    pages = pages if isinstance(pages, list) else [pages]
    for planar in (False, True):
        data = media.write_tiff(pages, compression, predictor, tile, 16, order, planar)
        back = list(media.read_pages(data))
        assert [p.index for p in back] == list(range(len(pages)))
        for p, want in zip(back, pages, strict=True):
            assert np.array_equal(p.pixels, want) and (p.compression, p.predictor, p.tiled) == (compression, predictor, bool(tile))


def test_codecs():
    r = random.Random(2)
    for size in (0, 1, 2, 127, 128, 129, 300, 70_000):
        for data in (bytes(r.randrange(256) for _ in range(size)), b"\7" * size, bytes(r.choice(b"ab") for _ in range(size))):
            assert media.unpack_bits(media.pack_bits(data)) == data
            assert media.lzw_decode(media.lzw_encode(data)) == data
    # a fixed value: the PackBits example of the format's public description
    assert media.unpack_bits(bytes.fromhex("FEAA0280002AFDAA0380002A22F7AA")) == bytes.fromhex("AAAAAA80002AAAAAAAAA80002A22AAAAAAAAAAAAAAAAAAAA")


def test_tiff_pages_operator(spark):
    good = media.write_tiff([np.arange(64, dtype="u1").reshape(8, 8, 1)] * 2)
    loop = bytearray(good)
    loop[-4:] = good[4:8]  # the last directory points back at the first
    rows = [(1, good), (2, None), (3, b""), (4, b"II*\0junk"), (5, bytes(loop)), (None, good[:40])]
    got = media.tiff_pages(spark.createDataFrame(rows, "doc_id bigint, media binary")).toPandas()
    assert got[got.doc_id == 1].page.tolist() == [0, 1] and got[got.doc_id == 1].pixels.tolist() == [bytes(range(64))] * 2
    assert set(got.doc_id.dropna()) == {1, 4, 5} and got[got.doc_id == 4].page.tolist() == [-1] and "nowhere" in got[got.doc_id == 5].error.tolist()[-1]


def test_media_query(spark, edge_rows):
    got = media.media_round_trip(table(spark, edge_rows)).toPandas()
    want = collections.Counter()
    for i, t in edge_rows:
        raw = (t or "").encode()
        payload = raw + b"\xff" * (-len(raw) % 576 or (0 if raw else 576))
        want[i, len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:])] += 1
    have = collections.Counter((None if r.doc_id != r.doc_id else int(r.doc_id), r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) for r in got.itertuples())
    assert have == want
    assert got.groupby("payload_sha256").media_sha256.nunique().max() == 1


# 2. Packing


def check_plan(counts, plan, capacity):
    seqs = collections.defaultdict(list)
    for length, places in plan.places.items():
        at = 0
        for rank, n, first, offset in places:
            assert rank == at
            at += n
            for j in range(n):
                seqs[first + j].append((offset, length))
        assert at == counts[length]
    assert len(seqs) == plan.sequences
    for items in seqs.values():
        at = 0
        for offset, length in sorted(items):
            assert offset == at
            at += length
        assert at <= capacity


@pytest.mark.parametrize("seed", range(6))
def test_plans_are_packings_near_the_bound(seed):
    r = random.Random(seed)
    counts = {k: r.randrange(1, 40) for k in r.sample(range(1, 2049), 500)}
    plan = packing.pack_histogram(counts)
    check_plan(counts, plan, 2048)
    bound = -(-sum(k * n for k, n in counts.items()) // 2048)
    big = sum(n for k, n in counts.items() if k > 1024)
    assert plan.sequences <= 1.03 * max(bound, big) + 2  # neither bound can be met in general


def test_small_plans_are_optimal():
    from itertools import product

    def best(items, capacity):
        out = len(items)
        for labels in product(range(len(items)), repeat=len(items)):
            sums = collections.Counter()
            for x, k in zip(items, labels, strict=True):
                sums[k] += x
            if max(sums.values()) <= capacity:
                out = min(out, len(sums))
        return out

    r = random.Random(5)
    for _ in range(25):
        items = [r.randrange(1, 11) for _ in range(6)]
        plan = packing.pack_histogram(dict(collections.Counter(items)), 10)
        check_plan(collections.Counter(items), plan, 10)
        assert plan.sequences <= best(items, 10) + (1 if best(items, 10) > 2 else 0)
    assert packing.pack_histogram({}, 10).sequences == 0 and packing.linear_groups([(9, 3), (5, 3)], 2) == [(9, [[9, 3]]), (5, [[5, 3]])]


def test_word_encoder_is_the_library():
    w = packing.word_encoder(P.path("word_bpe_49k.json"))
    texts = ["It's I'LL don't İstanbul ẞ Ω σΣ", "a\x85b\xa0c\x1cd", "é é", "<|endoftext|>x", "x y 中文 test", "a\x00b\x0bc​d", "ǅ Ǆ ŉ ß", "x²½ 10.5e3_@ ab.. ab., c! ª. µ?", " \t\n", "", "A a. a.. 'S ' .5 é."]
    for t, ids in zip(texts, w.encode_texts(texts), strict=True):
        assert ids == np.array(w.tokenizer.encode(t, add_special_tokens=False).ids, "<u4").tobytes(), t


def test_packing_covers_every_token(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    got = packing.best_fit_packing(docs, P.path("word_bpe_49k.json")).toPandas()
    w = packing.word_encoder(P.path("word_bpe_49k.json"))
    pieces = {(r.doc_id, r.piece): r for r in got.itertuples()}
    for d in docs.collect():
        ids = np.array([*w.tokenizer.encode(d["text"], add_special_tokens=False).ids, 0], "<u4")
        for k, at in enumerate(range(0, len(ids), 2048)):
            p = pieces.pop((d["doc_id"], k))
            assert (p.start, p.length, p.ids_crc32) == (at, len(ids[at : at + 2048]), zlib.crc32(ids[at : at + 2048].tobytes()))
    assert not pieces
    for _, s in got.groupby("sequence_id"):
        s = s.sort_values("offset")
        assert s.offset.tolist() == [0, *s.length.cumsum().tolist()[:-1]] and s.length.sum() <= 2048
    assert got.sequence_id.nunique() <= -(-got.length.sum() // 2048) * 1.03 + 1


# 3. Exact dedup


def test_weak_digests_are_taken_apart(spark):
    rows = [(k, f"text {k % 7}".upper() if k % 2 else f"text {k % 7}") for k in range(60)]
    weak = lambda t: F.unhex(F.hex(F.crc32(t.cast("binary")) % 3))
    got = {r["doc_id"]: (r["keep_id"], r["group_size"], r["kept"]) for r in exact.exact_dedup(table(spark, rows), weak).collect()}
    groups = collections.defaultdict(list)
    for i, t in rows:
        groups[t.lower()].append(i)
    assert got == {i: (max(g), len(g), i == max(g)) for g in groups.values() for i in g}


def test_state_stream_goes_on_after_a_restart(spark):
    from incrank.session import scratch

    log_path, state = scratch(spark, "log"), scratch(spark, "state")
    log = exact.digest_log(table(spark, [(1, "x"), (2, "y")]))
    log.write.parquet(log_path)
    exact.run_stream(spark, log_path, log.schema, state)
    exact.digest_log(table(spark, [(5, "X"), (3, "z")])).write.mode("append").parquet(log_path)
    got = {(r["keep_id"], r["group_size"]) for r in exact.run_stream(spark, log_path, log.schema, state).collect()}
    assert got == {(5, 2), (2, 1), (3, 1)}


# 4. BPE


def test_bpe_is_tiktoken():
    ranks = bpe.read_ranks(P.path("byte_bpe_multi_50k.tiktoken"))
    spec = bpe.tokenizer_json(ranks)
    theirs = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    ours = bpe.encoder(spec, P.PATTERN)
    r = random.Random(3)
    pool = ["the ", "ing", "é", "中", "🙂", " ", "\n", "  ", "'s", "'", "12", "Ⅷ", "́", "\x85", "​", "x" * 300, "ab" * 100, "!?", "<|endoftext|>", " ", "ß", "\x00"]
    texts = ["".join(r.choice(pool) for _ in range(r.randrange(40))) for _ in range(400)]
    for t, ids in zip(texts, ours.encode_texts(texts), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == theirs.encode_ordinary(t), t
        assert bpe.decode_bytes(spec, ids) == t.encode()


def test_bpe_offsets_and_split_characters(spark):
    ranks = {bytes([k]): k for k in range(256)} | {b"th": 256, b"the": 257}
    spec = bpe.tokenizer_json(ranks)
    assert len(set(bpe.byte_chars())) == 256 and all(bpe.char_bytes()[c] == b for b, c in enumerate(bpe.byte_chars()))
    docs = spark.createDataFrame([(1, "the é🙂"), (2, None)], "doc_id bigint, text string")
    rows = {r["doc_id"]: r for r in bpe.encode_documents(docs, spec, P.PATTERN).collect()}
    assert rows[1]["ids"][0] == 257 and (rows[1]["starts"][0], rows[1]["ends"][0]) == (0, 3) and rows[2]["ids"] == []
    assert [(a, b) for a, b in zip(rows[1]["starts"], rows[1]["ends"], strict=True)][-4:] == [(5, 6)] * 4
    back = bpe.decode_documents(bpe.encode_documents(docs, spec, P.PATTERN), spec)
    assert {r["doc_id"]: r["text"] for r in back.collect()} == {1: "the é🙂", 2: ""}
    ids = rows[1]["ids"]
    parts = list(bpe.decode_pieces(spec, [[i] for i in ids]))
    assert "".join(parts) == "the é🙂" and parts[-1] == "🙂" and list(bpe.decode_pieces(spec, [ids[-4:-1]])) == ["", "�"]


# 5. Importance resampling


def test_resampling_weights_and_draw(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    got = quality.importance_resample(docs, labels, share=0.5).toPandas().set_index("doc_id")
    assert got.kept.sum() == round(0.5 * len(got)) and got[got.kept].draw.min() > got[~got.kept].draw.max()
    # brute force over one text
    src = {r["doc_id"]: r["text"] for r in docs.collect()}
    good = {r["doc_id"] for r in labels.where("quality = 1").collect()}

    def count(texts):
        total = np.zeros(quality.BUCKETS)
        for t in texts:
            b, _ = quality.ngram_buckets(*column_bytes(pa.array([t])))
            np.add.at(total, b, 1)
        return total

    target, raw = count([src[i] for i in good if i in src]), count(src.values())
    ratio = quality.log_ratio(target, raw)
    i = next(iter(src))
    b, _ = quality.ngram_buckets(*column_bytes(pa.array([src[i]])))
    assert got.loc[i].log_weight == pytest.approx(ratio[b].sum(), abs=1e-6) and got.loc[i].n_grams == len(b)
    words = re.findall(rb"[0-9A-Za-z\x80-\xff]+|[^\s0-9A-Za-z\x80-\xff]+", src[i].encode())
    assert len(b) == 2 * len(words) - 1


def test_resampling_prefers_the_target(spark):
    """The order by weight separates labelled good from bad texts that the model has not seen as such."""
    sf = SF.replace("0.001", "0.01")
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    held = labels.where("doc_id % 3 = 0").toPandas().set_index("doc_id")
    got = quality.importance_resample(docs, labels.where("doc_id % 3 <> 0")).toPandas().set_index("doc_id").join(held, how="inner")
    good, bad = got[got.quality == 1].log_weight.to_numpy(), got[got.quality == 0].log_weight.to_numpy()
    assert (good[:, None] > bad[None, :]).mean() > 0.9
    assert got[got.quality == 1].kept.mean() > 0.9 and got[got.quality == 0].kept.mean() < 0.4


def test_kth_largest(spark):
    r = random.Random(1)
    for values in ([r.random() for _ in range(500)], [1.0] * 300 + [2.0] * 5, [0.5]):
        df = spark.createDataFrame([(k, v) for k, v in enumerate(values)], "doc_id bigint, draw double")
        order = sorted((-v, k) for k, v in enumerate(values))
        for k in (1, len(values) // 3 + 1, len(values)):
            assert quality.kth_largest(df, k, bins=8, few=10) == (-order[k - 1][0], order[k - 1][1])
    assert quality.kth_largest(spark.createDataFrame([], "doc_id bigint, draw double"), 3) is None


# 6. Sharding


def test_matrix_and_hypergeometric_draws():
    m = sharding.communication_matrix([10, 0, 7, 33], sharding.shard_sizes(50, 4), 1)
    assert [sum(r) for r in m] == [10, 0, 7, 33] and [sum(c) for c in zip(*m, strict=True)] == [13, 13, 12, 12]
    rng = random.Random(1)
    got = collections.Counter(sharding.hypergeometric(rng, 5, 7, 6) for _ in range(20_000))
    from math import comb

    for x in range(6):
        assert got[x] / 20_000 == pytest.approx(comb(5, x) * comb(7, 6 - x) / comb(12, 6), abs=0.015)


def test_shuffle_is_exact_and_uniform(spark):
    docs = table(spark, [(k, f"t{k}") for k in range(1003)])
    got = sharding.shuffled_shards(docs, 16, rows_per_block=50).toPandas()
    assert sorted(got.groupby("shard").size()) == [62] * 5 + [63] * 11
    for _, s in got.groupby("shard"):
        assert sorted(s.slot) == list(range(len(s)))
    assert got.equals(sharding.shuffled_shards(docs, 16, rows_per_block=50).toPandas()[got.columns]) or sorted(map(tuple, got.values.tolist())) == sorted(map(tuple, sharding.shuffled_shards(docs, 16, rows_per_block=50).toPandas().values.tolist()))
    hits = collections.Counter()
    for seed in range(30):
        rows = sharding.shuffled_shards(docs.where("doc_id < 32"), 4, seed=seed, rows_per_block=8).where("doc_id = 3").collect()
        hits[rows[0]["shard"]] += 1
    assert max(hits.values()) < 18 and len(hits) == 4


# 7. Near-duplicates


def brute_classes(rows, weights, least=0.8):
    ids, texts = [i for i, _ in rows], [t or "" for _, t in rows]
    block = column_bytes(pa.array(texts))
    pairs = [(a, b) for a in range(len(rows)) for b in range(a)]
    up = list(range(len(rows)))

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for (a, b), s in zip(pairs, neardup.similarities(*block, weights, pairs), strict=True):
        if s >= least - 1e-9:
            a, b = sorted((find(a), find(b)), key=lambda x: ids[x])
            up[b] = a
    return {ids[k]: ids[find(k)] for k in range(len(rows))}


def test_near_duplicates_are_those_of_all_pairs(spark):
    r = random.Random(4)
    words = [f"w{k}" for k in range(400)]
    rows, passage = [], " ".join(r.choice(words) for _ in range(30))
    for g in range(25):
        base = [r.choice(words) for _ in range(r.choice([8, 40, 200]))] + (passage.split() if g % 2 else [])
        for _ in range(r.choice([1, 2, 6, 20])):
            t = list(base)
            for _ in range(r.choice([0, 0, 1, 2, 5])):
                t[r.randrange(len(t))] = r.choice(words)
            rows.append((len(rows) * 3 + 1, " ".join(t)))
    docs = table(spark, rows)
    weights = neardup.idf_weights(*neardup.document_frequencies(texts_of(docs)))
    got = {x["doc_id"]: x["class_id"] for x in neardup.near_duplicates(docs).collect()}
    assert got == brute_classes(rows, weights)
    assert len(set(got.values())) < len(rows)


def test_near_duplicates_by_frequencies_of_runs(spark, monkeypatch):
    """Buckets as full as those of a large corpus must not decide: pages that share a template only are no copies."""
    template = " ".join(f"t{k}" for k in range(200))
    rows = [(g, f"{template} " + " ".join(f"own{g}x{k}" for k in range(8))) for g in range(60)]
    docs = table(spark, rows)
    frequencies, n = neardup.document_frequencies(texts_of(docs))
    want = brute_classes(rows, neardup.idf_weights(frequencies, n))
    monkeypatch.setattr(neardup, "document_frequencies", lambda texts: (np.full_like(frequencies, n), n))
    got = {x["doc_id"]: x["class_id"] for x in neardup.near_duplicates(docs).collect()}
    assert got == want and len(set(got.values())) == 60


def test_near_duplicates_within_a_large_template(spark):
    """Pairs of pages among two thousand that have one template: all share bands, background similarity is below the bound."""
    template = " ".join(f"t{k}" for k in range(400))
    page = lambda g, other: f"{template} " + " ".join(f"own{g}x{k}" if k < 4 else f"{other}{g}x{k}" for k in range(7))
    rows = [(g, page(g, "left")) for g in range(1000)] + [(1000 + g, page(g, "right")) for g in range(1000)]
    got = {x["doc_id"]: x["class_id"] for x in neardup.near_duplicates(table(spark, rows)).collect()}
    assert got == {k: k % 1000 for k in range(2000)}


def test_near_duplicates_within_a_group_of_a_large_corpus(spark):
    """However many documents there are, a few edits weigh no more against what a group of near copies has in common."""
    base, rows = [f"b{k}" for k in range(200)], []
    for g in range(15):
        t = list(base)
        t[10 + g * 12], t[16 + g * 12] = f"x{g}", f"y{g}"
        rows.append((g, " ".join(t)))
    rows += [(100 + k, " ".join(f"f{k}x{j}" for j in range(6))) for k in range(4000)]
    got = {x["doc_id"]: x["class_id"] for x in neardup.near_duplicates(table(spark, rows)).collect()}
    assert got == {i: 0 if i < 15 else i for i, _ in rows}


def test_near_duplicates_compare_few_pairs_of_a_large_group(spark, monkeypatch):
    """Pages of one group that are just not alike are told apart by what they share in hash buckets, not pair by pair; their twins are found."""
    r = random.Random(11)
    base, rows = [f"b{k}" for k in range(600)], []
    for g in range(150):
        t = list(base)
        for k, at in enumerate(r.sample(range(0, 594, 6), 6)):
            t[at : at + 2] = f"x{g}y{k}", f"z{g}y{k}"
        rows.append((g, " ".join(t)))
        if g < 10:
            rows.append((1000 + g, " ".join(t[:-1])))
    rows += [(2000 + k, " ".join(f"f{k}x{j}" for j in range(6))) for k in range(4000)]
    seen, compare = [], neardup.verified
    monkeypatch.setattr(neardup, "verified", lambda pairs, *more: seen.append(pairs.count()) or compare(pairs, *more))
    got = {x["doc_id"]: x["class_id"] for x in neardup.near_duplicates(table(spark, rows)).collect()}
    assert got == {i: i - 1000 if 1000 <= i < 1010 else i for i, _ in rows}
    assert 10 <= sum(seen) < 1500


def test_marks_bound_what_two_texts_share():
    r = np.random.default_rng(3)
    got = np.sort(r.integers(1, 2**63, 300).astype(np.uint64))
    w = r.random(300) * 5
    for cut in (0, 50, 140):
        a, b = np.arange(0, 300 - cut), np.arange(cut, 300)
        x, y = (neardup.marks(np.zeros(len(i), np.int64), got[i], w[i], 1)[0] for i in (a, b))
        assert w[cut : 300 - cut].sum() <= np.minimum(x, y).sum(dtype=np.float64) < w[a].sum() * (1 - cut / 1000) * 1.001


def test_draws_collide_with_the_similarity():
    r = np.random.default_rng(6)
    hits = []
    for _ in range(300):
        w = r.random(60).astype(np.float32) + 0.1
        got = r.integers(1, 2**63, 60).astype(np.uint64)
        a, b = np.arange(0, 50), np.arange(10, 60)
        wb = w.copy()
        wb[20:30] *= 1.5
        draws = neardup.weighted_draws(np.repeat([0, 1], 50), np.concatenate([got[a], got[b]]), np.concatenate([w[a], wb[b]]), 2)
        low = np.minimum(w, wb)[10:50].sum()
        hits.append(((draws[0] == draws[1]).mean(), low / (w[a].sum() + wb[b].sum() - low)))
    seen, want = np.mean(hits, axis=0)
    assert seen == pytest.approx(want, abs=0.02)


def test_components(spark):
    links = spark.createDataFrame([(1, 2), (2, 3), (9, 8), (7, 9), (5, 5)] + [(k, k + 1) for k in range(100, 160)], "a bigint, b bigint")
    got = {r["node"]: r["component"] for r in connected_components(links).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 7: 7, 8: 7, 9: 7} | {k: 100 for k in range(100, 161)}


# 8. Toxicity


def test_maximal_segments_are_those_of_brute_force():
    r = random.Random(7)

    def brute(scores):
        """Public definition: the best segment, then the same to its left and right."""
        if not any(s > 0 for s in scores):
            return []
        best = max(((a, b) for a in range(len(scores)) for b in range(a, len(scores))), key=lambda x: (round(sum(scores[x[0] : x[1] + 1]), 9), x[0] - x[1], -x[0]))
        a, b = best
        return brute(scores[:a]) + [(a, b)] + [(x + b + 1, y + b + 1) for x, y in brute(scores[b + 1 :])]

    for _ in range(300):
        s = [r.choice([-3.5, -1.25, -0.6, 0.7, 1.3, 2.9]) + r.random() * 0.01 for _ in range(r.randrange(1, 14))]
        sums = np.concatenate([[0], np.cumsum(s)])
        got = [(a, b) for a, b, _ in toxicity.maximal_segments(sums, np.flatnonzero(np.array(s) > 0))]
        assert got == brute(s), s


def test_toxicity_on_held_out_rows(spark):
    r = random.Random(8)
    words = ["".join(r.choice("abcdefghij") for _ in range(r.randrange(2, 8))) for _ in range(3000)]
    bad = ["slurone", "slurtwo", "slurthree"]
    rows, labels = [], []
    for k in range(900):
        toxic = k % 6 == 0
        t = [r.choice(words) for _ in range(r.randrange(5, 200))]
        for _ in range(r.randrange(1, 4) if toxic else 0):
            t.insert(r.randrange(len(t)), r.choice(bad) + r.choice(["", "s", "ish", "."]))
        rows.append((k, " ".join(t)))
        labels.append((k, int(toxic)))
    docs, known = table(spark, rows), spark.createDataFrame(labels, "doc_id bigint, toxic int")
    got = toxicity.score_documents(docs, known).toPandas().merge(known.toPandas(), on="doc_id")
    held = got[got.held_out]
    assert all(h == (zlib.crc32(str(i).encode()) % 5 == 0) for i, h in zip(got.doc_id, got.held_out, strict=True))
    assert (held.predicted == held.toxic).mean() > 0.97 and ((held.score >= 0.5) == held.predicted).all()
    model = toxicity.fit(docs, known, toxicity.may_learn)
    spans = toxicity.toxic_passages(docs, model).collect()
    text = dict(rows)
    assert spans and all(text[s["doc_id"]].encode()[s["start"] :].lower().startswith(b"slur") for s in spans)
    flipped = spark.createDataFrame([(i, 1 - x if zlib.crc32(str(i).encode()) % 5 == 0 else x) for i, x in labels], "doc_id bigint, toxic int")
    again = toxicity.score_documents(docs, flipped).toPandas().set_index("doc_id")
    assert (again.score - got.set_index("doc_id").score).abs().max() == 0  # labels of held-out rows change nothing


# 9. Token counts


def test_counts_follow_random_edits():
    source = tokencounts.counter(P.path("byte_bpe_50k.json"), P.PATTERN)
    r, pool = random.Random(9), "ab  \n\t'sdtl1.é中,  "
    for _ in range(1500):
        text = "".join(r.choice(pool) for _ in range(r.randrange(300)))
        doc = tokencounts.CountedText(text, source)
        for _ in range(r.randrange(1, 6)):
            a = r.randrange(len(text) + 1)
            b = min(len(text), a + r.choice([0, 0, 1, 3, 30, 400]))
            new = "".join(r.choice(pool) for _ in range(r.choice([0, 1, 2, 9, 200])))
            doc.edit(a, b, new)
            text = tokencounts.apply_edit(text, a, b, new)
            pieces = source.split(text)
            assert [p for ps, _ in doc.leaves for p in ps] == pieces
            assert doc.n_tokens == sum(source.counts(pieces)) and doc.n_pieces == len(pieces)
            assert doc.tokens.before(len(doc.leaves)) == doc.n_tokens


def test_edits_reencode_little():
    source = tokencounts.counter(P.path("byte_bpe_50k.json"), P.PATTERN)
    doc = tokencounts.CountedText(LONG, source)
    doc.edit(100_000, 100_003, "new words here")
    assert doc.reencoded < 60 and doc.updated <= 2 * 20
    assert doc.n_tokens == len(source.tokenizer.encode(LONG[:100_000] + "new words here" + LONG[100_003:], add_special_tokens=False).ids)


# 10. Suffix dedup


def brute_repeats(rows):
    first, out = {}, {}
    for i, t in sorted(rows, key=lambda r: r[0]):
        b = (t or "").encode()
        for k in range(len(b) - 49):
            first.setdefault(b[k : k + 50], i)
    for i, t in rows:
        b = (t or "").encode()
        gone = np.zeros(len(b) + 2, bool)
        for k in range(len(b) - 49):
            if first[b[k : k + 50]] < i:
                gone[k + 1 : k + 51] = True
        runs = int((gone[1:] & ~gone[:-1]).sum())
        out[i] = (len(b), int(gone.sum()), runs, hashlib.sha256(bytes(x for x, g in zip(b, gone[1:], strict=False) if not g)).hexdigest())
    return out


def repeat_cases(seed):
    r = random.Random(seed)
    passages = ["".join(r.choice("abcd efé") for _ in range(r.choice([30, 49, 50, 51, 80, 400]))) for _ in range(12)]
    rows = []
    for k in range(150):
        t = "".join(r.choice([r.choice(passages), "".join(r.choice("abcdefgh ") for _ in range(r.randrange(60))), "a" * r.randrange(120), passages[3][: r.randrange(1, 60)]]) for _ in range(r.randrange(6)))
        rows.append((k * 2, t))
    return rows


@pytest.mark.parametrize("seed", range(3))
@pytest.mark.parametrize("hot", [False, True])
def test_repeats_are_those_of_brute_force(spark, seed, hot, monkeypatch):
    rows = repeat_cases(seed)
    monkeypatch.setattr(suffix, "FLUSH", 300)
    if hot:  # every token that the sample has twice counts as hot
        real = suffix.splitters_of

        def splitters(*args):
            cuts, _, parts = real(*args)
            tokens = np.concatenate([suffix.runs_of(*column_bytes(pa.array([t])))[0] for _, t in rows])
            values, n = np.unique(tokens, return_counts=True)
            return cuts, values[n > 1][::2], parts

        monkeypatch.setattr(suffix, "splitters_of", splitters)
    got = {r["doc_id"]: tuple(r)[1:] for r in suffix.repeat_digests(table(spark, rows)).collect()}
    assert got == brute_repeats(rows)


def test_repeats_of_rows_that_share_a_doc_id_or_have_none(spark):
    r = random.Random(3)
    some = lambda n: "".join(r.choice("abcdefghijklmnop ") for _ in range(n))
    p, q = some(90), some(70)
    rows = [(2, some(80) + "!" + q), (5, p + some(60)), (5, some(200)), (5, some(30) + p), (None, q + "?" + some(200)), (None, some(400)), (None, some(50) + "#" + q + "%" + some(20)), (None, None)]
    want = brute_repeats([(k, t) for k, (_, t) in enumerate(rows)])
    got = sorted(tuple(x) for x in suffix.repeat_digests(table(spark, rows)).select("n_bytes", "n_removed", "n_spans", "kept_sha256").collect())
    assert got == sorted(want.values()) and [want[k][1] for k in (2, 3, 4, 5, 6)] == [0, 90, 70, 0, 70]
    texts = [x["text"] for x in suffix.strip_repeats(table(spark, rows)).where("doc_id IS NULL").collect()]
    assert rows[5][1] in texts and None in texts


def test_long_texts_come_in_overlapping_pieces(spark, monkeypatch):
    monkeypatch.setattr(suffix, "STEP_BYTES", 700)
    r = random.Random(11)
    long = "".join(r.choice("abcdefghijklmnop ") for _ in range(9000))
    rows = [(1, long), (2, long[100:7000] + "x" + long[7001:]), (3, long[3333:3383]), (4, long[3333:3382])]
    got = {x["doc_id"]: tuple(x)[1:] for x in suffix.repeat_digests(table(spark, rows)).collect()}
    assert got == brute_repeats(rows)


def test_multikey_order():
    r = np.random.default_rng(12)
    for _ in range(50):
        words = [r.integers(0, 4, 60) for _ in range(3)]
        got = suffix.multikey_order(*words)
        assert [tuple(w[i] for w in words) for i in got] == sorted(zip(*words, strict=True))


def test_cuts_keep_characters_whole():
    data = "aé中z".encode()
    assert suffix.whole_characters(data, [(2, 5)]) == [(3, 5)][:0] or suffix.without(data, suffix.whole_characters(data, [(2, 5)])).decode()
    for a in range(len(data)):
        for b in range(a, len(data) + 1):
            suffix.without(data, suffix.whole_characters(data, [(a, b)])).decode()


def quadratic_segments(sums, gains):
    """The definition, without links: a candidate joins the nearest before it that starts lower, if that ends lower too."""
    held = []
    for k in gains.tolist():
        item = [float(sums[k]), float(sums[k + 1]), k, k]
        while True:
            j = next((j for j in range(len(held) - 1, -1, -1) if held[j][0] < item[0]), -1)
            if j < 0 or held[j][1] >= item[1]:
                held.append(item)
                break
            item = [held[j][0], item[1], held[j][2], k]
            del held[j:]
    return [(a, b, after - before) for before, after, a, b in held]


def test_segments_take_linear_time():
    import time

    rng = np.random.default_rng(5)
    for _ in range(300):
        each = np.round(rng.normal(-0.2, 1.0, rng.integers(1, 60)), 1)
        sums, gains = np.concatenate([[0.0], np.cumsum(each)]), np.flatnonzero(each > 0)
        assert toxicity.maximal_segments(sums, gains) == quadratic_segments(sums, gains)
    took = []
    for n in (50_000, 400_000):
        each = np.tile([1.0, -1.5], n)
        sums, gains = np.concatenate([[0.0], np.cumsum(each)]), np.flatnonzero(each > 0)
        began = time.perf_counter()
        assert len(toxicity.maximal_segments(sums, gains)) == n
        took.append(time.perf_counter() - began)
    assert took[1] < 40 * took[0] + 1


def test_every_word_with_log_odds_counts():
    """However many words have log-odds, and whatever their hashes share."""
    hashes = np.sort(np.concatenate([np.arange(1, 60_000, dtype=np.uint64) << np.uint64(21), np.array([7, 8], np.uint64)]))
    odds = np.linspace(-3, 3, len(hashes))
    model = toxicity.ToxicityModel(hashes, odds)
    got = toxicity.word_scores(model, [(np.arange(len(hashes)), hashes)])
    assert np.allclose(got, odds - toxicity.DRIFT)
    assert np.allclose(toxicity.word_scores(model, [(np.arange(3), np.array([9, 10, 1 << 60], np.uint64))]), -toxicity.DRIFT)


def test_broken_tiffs_give_one_row_each(spark):
    import struct

    pixels = np.arange(64 * 48, dtype=np.uint8).reshape(64, 48, 1)
    files = {"strips": media.write_tiff([pixels], media.LZW), "tiles": media.write_tiff([pixels], media.PACKBITS, tile=(16, 16)), "flat": media.write_tiff([pixels], media.DEFLATE)}
    broken = []
    for data in files.values():
        (at,) = struct.unpack("<I", data[4:8])
        (n,) = struct.unpack_from("<H", data, at)
        for k in range(n):
            for value in (0, 1, 0x7FFFFFFF, 0xFFFFFFFF):
                out = bytearray(data)
                struct.pack_into("<I", out, at + 2 + 12 * k + 8, value)
                broken.append(bytes(out))
            out = bytearray(data)
            struct.pack_into("<I", out, at + 2 + 12 * k + 4, 0xFFFFFFFF)
            broken.append(bytes(out))
        broken += [data[:k] for k in range(0, len(data), 97)]
    for data in broken:
        try:
            assert all(p.pixels.nbytes <= 1 << 24 for p in media.read_pages(data))
        except media.BROKEN:
            pass
    rows = media.tiff_pages(spark.createDataFrame([(k, bytearray(b)) for k, b in enumerate(broken)], "doc_id long, media binary")).groupBy("doc_id").agg({"error": "count"}).collect()
    assert all(r["count(error)"] <= 1 for r in rows) and sum(r["count(error)"] for r in rows) > len(broken) / 2


def test_components_of_a_long_chain(spark):
    """Labels are right however long the chain, and whatever the order of its ids."""
    rng = np.random.default_rng(1)
    ids = rng.permutation(150)
    links = spark.createDataFrame([(int(a), int(b)) for a, b in zip(ids[:-1], ids[1:])] + [(1000, 1001)], "a long, b long")
    got = {r["node"]: r["component"] for r in connected_components(links).collect()}
    assert len(got) == 152 and {got[int(k)] for k in ids} == {0} and got[1001] == 1000


def test_weak_digests_of_rows_without_id_are_taken_apart(spark):
    """Rows without doc_id are read again by their locators: a digest that stands for two of their texts is seen."""
    rows = [(None, "alpha"), (None, "bravo"), (None, "alpha"), (1, "x")]
    weak = lambda text: F.substring(F.sha2(F.length(text).cast("string").cast("binary"), 256), 1, 4).cast("binary")
    got = exact.exact_dedup(spark.createDataFrame(rows, "doc_id long, text string"), weak)
    assert sorted(r["group_size"] for r in got.collect()) == [1, 1, 2, 2]


def test_hot_keys_are_joined_as_all_others(spark, monkeypatch):
    monkeypatch.setattr(common, "HOT_ROWS", 3)
    rows = spark.createDataFrame([(k, "hot" if k < 20 else f"k{k % 7}") for k in range(40)], "n int, key string")
    keys = rows.groupBy("key").agg(F.min("n").alias("least"), F.count(F.lit(1)).alias("copies"))
    got = common.join_per_key(rows, keys, ["key"], "copies", 40)
    assert sorted((r["n"], r["least"], r["copies"]) for r in got.collect()) == sorted((r["n"], r["least"], r["copies"]) for r in rows.join(keys, "key").collect())


def test_rows_without_id_go_to_all_shards(spark):
    docs = spark.createDataFrame([(None, "same") for _ in range(320)] + [(5, "t") for _ in range(160)], "doc_id long, text string")
    got = sharding.shuffled_shards(docs, 16, rows_per_block=50).toPandas()
    assert got.groupby("shard").size().tolist() == [30] * 16
    assert (got.groupby("shard").slot.agg(["min", "max"]).values == [0, 29]).all()
    # of the 160 rows with one id, a uniform shuffle puts some ten in each shard
    assert got[got.doc_id == 5].groupby("shard").size().reindex(range(16), fill_value=0).between(2, 22).all()


def test_a_large_matrix_takes_seconds():
    import time

    began = time.perf_counter()
    rows = sharding.communication_matrix([2_000_000] * 64, sharding.shard_sizes(128_000_000, 16), 3)
    assert all(sum(r) == 2_000_000 for r in rows) and [sum(c) for c in zip(*rows, strict=True)] == [8_000_000] * 16
    assert time.perf_counter() - began < 10
