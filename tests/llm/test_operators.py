"""Each operator against brute force, and on nulls, empty and long texts, ties, repeated rows and clashing columns."""

from __future__ import annotations

import base64
import bisect
import hashlib
import itertools
import math
import random
import re
import time
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
import tiktoken
from pyspark.sql import functions as F

import public_tokenizers
from gridsparse.llm import bpe, boosting, common, components, language, media, mixing, neardup, pii, quality, search, token_counts, toxicity

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, size long, target string, component_id string, kept string, score string, key string, block string"


def table(spark, rows):
    """Documents with further columns whose names operators use themselves."""
    return spark.createDataFrame([(i, t, g, s, len(t) if t is not None else None, 7, "x", "y", "z", "w", "k", "b") for i, t, g, s in rows], SCHEMA)


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(5)
    words = ["alpha", "Beta", "gamma", "δelta", "the", "of", "naïve", "x" * 40, "1999", "end."]
    text = lambda n: " ".join(rng.choice(words) + str(rng.randrange(9)) for _ in range(n))
    out = [(k, text(rng.randrange(3, 60)), rng.choice(["en", "fr", None]), rng.choice(["a", "b", None])) for k in range(60)]
    out += [(60, None, "en", "a"), (61, "", "en", None), (62, " \n\t ", None, "b"), (63, text(20_000), "en", "a"), (64, "one", "fr", "b"), (65, "!!! ???", None, None)]
    out += [(66, out[3][1], "en", "a"), (5, out[5][1], out[5][2], out[5][3]), (None, out[3][1], "en", "a"), (None, None, None, None)]
    near = out[7][1].split(" ")
    out += [(100 + k, " ".join([*near[: k], "changed", *near[k:]]), "en", "c") for k in range(0, len(near), max(1, len(near) // 6))]
    return out


@pytest.fixture(scope="module")
def docs(spark, rows):
    return table(spark, rows)


@pytest.fixture(scope="module")
def none(spark):
    return table(spark, [])


def sets_of(rows, width):
    out = {}
    for k, (_, t, _, _) in enumerate(rows):
        w = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        out[k] = {tuple(w[a : a + width]) for a in range(len(w) - width + 1)} if len(w) >= width else ({tuple(w)} if w else set())
    return out


# -- 1 ---------------------------------------------------------------------------
def brute_targets(sizes: dict, weights=(5, 2, 1)):
    order = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: weights[k % 3] for k, s in enumerate(order)}
    total, fixed = 1.5 * sum(sizes.values()), {}
    while True:
        free = [s for s in order if s not in fixed]
        left = total - sum(fixed.values())
        share = {s: left * weight[s] / sum(weight[f] for f in free) for s in free}
        over = [s for s in free if share[s] > 2 * sizes[s]]
        if not over:
            return fixed | share
        fixed |= {s: 2.0 * sizes[s] for s in over}


def test_mixing(spark, docs, rows):
    got = mixing.assign(docs).collect()
    assert len(got) == len(rows)
    sizes = Counter()
    for _, t, _, s in rows:
        sizes[s] += len(WORD.findall(t or ""))
    want, taken = brute_targets(sizes), Counter()
    for r in got:
        assert r["source_size"] == sizes[r["source"]] and math.isclose(r["target"], want[r["source"]])
        assert r["taken"] == r["copies"] * r["size"] <= 2 * r["size"] and len(r["shards"]) == r["copies"]
        taken[r["source"]] += r["taken"]
    largest = max(r["size"] for r in got)
    for s, t in want.items():
        assert abs(taken[s] - t) <= largest
    again = {(r["doc_id"], r["taken"], tuple(r["shards"])) for r in mixing.assign(docs).collect()}
    assert again == {(r["doc_id"], r["taken"], tuple(r["shards"])) for r in got}
    mixed = mixing.mix(docs)
    assert mixed.count() == sum(r["copies"] for r in got) and mixed.columns[: len(docs.columns)] == docs.columns


def test_mixing_many_documents(spark):
    many = spark.range(4000).select(F.col("id").alias("doc_id"), F.repeat(F.lit("w "), (F.col("id") % 17).cast("int")).alias("text"), F.when(F.col("id") % 3 > 0, F.lit("hot")).otherwise(F.concat(F.lit("s"), F.col("id") % 5)).alias("source"))
    got = mixing.assign(many).groupBy("source").agg(F.first("target").alias("t"), F.sum("taken").alias("n")).collect()
    assert all(abs(r["t"] - r["n"]) <= 16 for r in got)
    shards = mixing.mix(many).groupBy("mix_shard").count().collect()
    assert len(shards) == 8 and max(r["count"] for r in shards) < 3 * min(r["count"] for r in shards)


def test_mixing_null_ids_and_clashing_names(spark):
    rows = [(None if k % 2 else k, "w " * (k % 11 + 1), "s" if k % 5 else None, 1, "x") for k in range(300)]
    frame = spark.createDataFrame(rows, "doc_id long, text string, source string, mix_shard long, Mix_Order string")
    got = mixing.assign(frame).collect()
    left = {}
    for r in got:
        left[r["source"]] = left.get(r["source"], r["target"]) - r["taken"]
    taken = {(r["doc_id"], r["source"], r["size"]): r["copies"] for r in got}
    assert len(left) == 2 and all(0 <= x <= 11 * 30 for x in left.values()) and len(got) == 300, left
    mixed = mixing.mix(frame)
    assert mixed.columns == [*frame.columns, "_mix_shard", "_mix_order"] and mixed.count() == sum(r["copies"] for r in got)
    assert sum(n for (i, _, _), n in taken.items() if i is None) > 0


def test_mixing_meets_the_target_past_a_long_document(spark):
    size = F.when(F.col("id") % 1000 == 0, F.lit(30_000)).otherwise(F.col("id") % 13 + 20)
    many = spark.range(4000).select(F.col("id").alias("doc_id"), F.repeat(F.lit("w "), size.cast("int")).alias("text"), F.concat(F.lit("s"), F.floor(F.col("id") / 1000).cast("string")).alias("source"))
    for seed in range(1, 4):
        left, untaken = {}, {}
        for r in mixing.assign(many, seed=seed).collect():
            left[r["source"]] = left.get(r["source"], r["target"]) - r["taken"]
            if r["copies"] <= r["target"] // r["source_size"]:
                untaken.setdefault(r["source"], []).append(r["size"])
        assert len(left) == 4 and all(x >= 0 for x in left.values())
        assert all(x < min(untaken.get(s, [math.inf])) for s, x in left.items()), left


def test_hypergeometric_law(spark):
    draw = mixing.hypergeometric(F.lit(50).cast("long"), F.lit(20).cast("long"), F.lit(15).cast("long"), mixing.uniform(F.lit(3), F.col("id")))
    seen = {r["x"]: r["count"] for r in spark.range(5000).select(draw.alias("x")).groupBy("x").count().collect()}
    chi = sum((seen.get(x, 0) - e) ** 2 / e for x in range(2, 12) if (e := 5000 * math.comb(20, x) * math.comb(30, 15 - x) / math.comb(50, 15)) > 5)
    assert chi < 35


# -- 2 and 5 -----------------------------------------------------------------------
@pytest.fixture(scope="module")
def library():
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(public_tokenizers.path(bpe.VOCABULARY), "rb"))}
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe(docs, rows, library):
    got = Counter((r["doc_id"], tuple(r["ids"]), r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) for r in bpe.encode_documents(docs).collect())
    want = Counter()
    for i, t, _, _ in rows:
        ids = library.encode_ordinary(t or "")
        want[i, tuple(ids), len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()] += 1
    assert got == want


def test_bpe_random_and_edits(library):
    coder, rng = bpe.encoder(), random.Random(1)
    for _ in range(3000):
        text = "".join(rng.choice(["a", "b", "th", " ", "\n", "é", "ß", "日", "🙂", "'s", "12", " ", "\x1c", "_"]) for _ in range(rng.randrange(25)))
        assert coder.encode(text) == library.encode_ordinary(text) and coder.decode(coder.encode(text)).decode() == text
    raw = b"the internationalization of andersonian things" * 3
    last = coder.extend(raw, [])
    assert coder.tokens_of(raw, last) == coder.search(raw)
    assert coder.extend(raw + b"more", list(last)) == coder.extend(raw + b"more", [])
    for _ in range(60):
        a = rng.randrange(len(raw))
        new, table, fresh = coder.edit(raw, last, a, min(len(raw), a + 2), b"xy" * rng.randrange(3))
        assert table == coder.extend(new, []) and fresh <= len(new)


def test_bpe_encodes_by_the_prefix_table(library, monkeypatch):
    own = bpe.PrefixEncoder(bpe.encoder().ranks, public_tokenizers.PATTERN)
    monkeypatch.setattr(own, "search", None)
    text = "unquestionablyzzq xqjkvbn 12345678 naïveté"
    assert own.encode(text) == library.encode_ordinary(text)


def test_token_counts(docs, rows, library):
    got = sorted(((r["doc_id"] is None, r["doc_id"], r["n_tokens"], tuple(r["section_tokens"])) for r in token_counts.count_sections(docs, "first").collect()), key=str)
    want = []
    for i, t, _, _ in rows:
        raw, at = (t or "").encode(), 0
        lines = raw.splitlines(keepends=True) if b"\r" not in raw else None
        starts = np.cumsum([0] + [len(x) for x in lines])[:-1] if lines else []
        counts = [0] * len(starts)
        for token in library.encode_ordinary(t or ""):
            counts[int(np.searchsorted(starts, at, side="right")) - 1] += 1
            at += len(library.decode_single_token_bytes(token))
        want.append((i is None, i, sum(counts), tuple(counts)))
    assert got == sorted(want, key=str)


def test_attribution_rules():
    first, last, starts = np.array([0, 3, 7]), np.array([2, 6, 8]), np.array([0, 4, 6])
    assert token_counts.attribute(first, last, starts, "first")[0].tolist() == [2, 0, 1]
    assert token_counts.attribute(first, last, starts, "last")[0].tolist() == [1, 0, 2]
    counts, crossing = token_counts.attribute(first, last, starts, "most")
    assert counts.tolist() == [1, 1, 1] and crossing == 1


def test_token_spans_and_fields(spark, docs, rows, library):
    texts = Counter((i, t or "") for i, t, _, _ in rows)
    for r in token_counts.token_spans(docs).collect():
        raws, at = [library.decode_single_token_bytes(x) for x in r["ids"]], 0
        text = b"".join(raws).decode()
        texts[r["doc_id"], text] -= 1
        starts = list(itertools.accumulate(len(c.encode()) for c in text))
        for raw, first, last in list(zip(raws, r["first"], r["last"], strict=True))[:500]:
            assert first == bisect.bisect_right(starts, at) and last == bisect.bisect_right(starts, at + len(raw) - 1)
            at += len(raw)
    assert not +texts
    frame = spark.createDataFrame([(1, "Ein Titel", "naïve\nbody text", "x"), (2, None, "", None), (3, "", "a b", "")], "doc_id long, title string, body string, note string")
    got = {r["doc_id"]: r for r in token_counts.count_fields(frame, ["title", "body", "note"], "first").collect()}
    for i, parts in {1: ("Ein Titel\n", "naïve\nbody text\n", "x"), 2: ("\n", "\n", ""), 3: ("\n", "a b\n", "")}.items():
        ids, at, want = library.encode_ordinary("".join(parts)), 0, [0, 0, 0]
        cuts = list(itertools.accumulate(len(p.encode()) for p in parts))
        for x in ids:
            want[min(2, bisect.bisect_right(cuts, at))] += 1
            at += len(library.decode_single_token_bytes(x))
        assert list(got[i]["field_tokens"].values()) == want and got[i]["n_tokens"] == len(ids)


def test_bpe_classes_are_the_library_s(library):
    rng, coder = random.Random(9), bpe.encoder()
    points = [c for c in range(0x20, 0x33480) if not 0xD800 <= c < 0xE000] + list(range(0xE0000, 0xE0200))
    for a in range(0, len(points), 4000):
        text = "".join(f"a{chr(c)}1" for c in points[a : a + 4000])
        assert coder.encode(text) == library.encode_ordinary(text)
    for _ in range(300):
        text = "".join(chr(rng.choice(points)) for _ in range(40))
        assert coder.encode(text) == library.encode_ordinary(text)


def test_bpe_long_texts_of_every_kind(library):
    coder = bpe.encoder()
    for unit, times in (("a", 200_000), (" ", 200_000), ("\n ", 100_000), ("é", 100_000), ("日本", 50_000), ("!?", 100_000), ("1", 200_000), ("ab1 ", 50_000), ("🙂", 50_000)):
        assert coder.encode(unit * times) == library.encode_ordinary(unit * times)


def test_bpe_edits_of_documents(spark, library):
    rng = random.Random(12)
    parts = ["word", " ", "  ", "\n", "'s", "'re", "l", "é", "12", "!!", "日", "zzqx"]
    make = lambda n: "".join(rng.choice(parts) for _ in range(n))
    cases = []
    for k in range(400):
        text = make(rng.randrange(30))
        start = rng.randrange(len(text) + 1)
        cases.append((k, text, start, rng.randrange(start, len(text) + 1), make(rng.randrange(4))))
    cases += [(1000, None, None, None, "new"), (1001, "abc", 99, -5, None), (1002, make(5000), 7000, 7003, "x")]
    got = {r["doc_id"]: r for r in bpe.encode_edited(spark.createDataFrame(cases, "doc_id long, text string, start int, stop int, new string")).collect()}
    for k, text, start, stop, new in cases[:400] + cases[402:]:
        assert got[k]["ids"] == library.encode_ordinary(text[:start] + new + text[stop:]), (text, start, stop, new)
    assert got[1000]["ids"] == library.encode_ordinary("new") and got[1001]["ids"] == library.encode_ordinary("abc")
    assert got[1002]["pieces_encoded"] <= 12 < got[1002]["pieces"]
    held = bpe.Encoded(bpe.encoder(), "")
    for k in range(60):
        held.append(more := rng.choice(["zz", "q", " ", "x1", "é"]))
        assert held.ids().tolist() == library.encode_ordinary(held.text), (held.text, more)


# -- 3 ---------------------------------------------------------------------------
def test_media(docs, rows):
    got = media.store_documents(docs, keep_media=True).collect()
    assert len(got) == len(rows)
    want = Counter()
    for _, t, _, _ in rows:
        payload = media.payload_of((t or "").encode())
        want[len((t or "").encode()), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:])] += 1
    assert Counter((r["n_bytes"], r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) for r in got) == want
    for r in got:
        assert hashlib.sha256(r["media"]).hexdigest() == r["media_sha256"] and len(r["media"]) == r["media_bytes"]
    assert len({(r["n_bytes"], r["payload_sha256"], r["media_sha256"], r["feature"]) for r in got}) == len({r["payload_sha256"] for r in got})


def test_media_any_bytes():
    rng = np.random.default_rng(0)
    payloads = [bytes([128]) * 128, bytes(range(256)) * 3, rng.integers(0, 256, 64 * 99, dtype=np.uint8).tobytes(), bytes([255]) * 64, bytes(64)]
    files = media.pack(payloads)
    frames = [media.parse(f) for f in files]
    assert [media.unpack(f, c) for f, c in zip(frames, media.decode(files, frames), strict=True)] == payloads


def test_colour_file_without_restarts(spark):
    """Three components, luminance 2 x 2, one scan without restart markers: the thumbnail is the luminance DCs."""
    wide, high = 3, 2
    dcs = np.arange(wide * high * 4) * 8 - 80
    dc, ac = media.DC_TABLE, media.AC_TABLE
    bits, level, k = "", [0, 0, 0], 0

    def put(component, value):
        nonlocal bits
        d = value - level[component]
        level[component] = value
        size = abs(d).bit_length()
        bits += format(dc.code[size], f"0{dc.length[size]}b") + (format(d if d > 0 else d + (1 << size) - 1, f"0{size}b") if size else "")
        bits += format(ac.code[0], f"0{ac.length[0]}b")

    for _ in range(wide * high):
        for _ in range(4):
            put(0, int(dcs[k]))
            k += 1
        put(1, 3)
        put(2, -3)
    bits += "1" * (-len(bits) % 8)
    scan = bytes(int(bits[a : a + 8], 2) for a in range(0, len(bits), 8)).replace(b"\xff", b"\xff\x00")
    frame = b"\x08" + (16 * high).to_bytes(2, "big") + (16 * wide).to_bytes(2, "big") + b"\x03\x01\x22\x00\x02\x11\x00\x03\x11\x00"
    tables = media._segment(0xDB, b"\x00" + b"\x01" * 64) + media._segment(0xC4, b"\x00" + dc.segment) + media._segment(0xC4, b"\x10" + ac.segment)
    file = media.HEAD + tables + media._segment(0xC0, frame) + media._segment(0xDA, b"\x03\x01\x00\x02\x00\x03\x00\x00\x3f\x00") + scan + b"\xff\xd9"
    want = np.clip((dcs + 4) // 8 + 128, 0, 255).reshape(high, wide, 2, 2).transpose(0, 2, 1, 3).reshape(2 * high, 2 * wide)
    parsed = media.parse(file)
    assert (media.luminance(parsed, media.decode([file], [parsed])[0]) == want).all()
    rows = media.thumbnails(spark.createDataFrame([(bytearray(file),), (bytearray(b"junk"),), (None,)], "content binary")).collect()
    assert sorted((r["width"] or 0, r["thumb_height"] or 0, r["error"] is None) for r in rows) == [(0, 0, False), (0, 0, False), (48, 4, True)]


# -- 4 ---------------------------------------------------------------------------
def test_search(spark, docs, rows):
    queries = docs.where("doc_id % 10 = 0")
    got = {}
    for r in search.search(docs, queries, top=5).collect():
        got.setdefault(r["query"], []).append((r["rank"], r["doc_id"], r["score"]))
    words = {k: Counter(WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))) for k, (i, t, _, _) in enumerate(rows) if i is not None}
    mean = sum(sum(c.values()) for c in words.values()) / len(words)
    df = Counter(w for c in words.values() for w in c)
    for k in words:
        i = rows[k][0]
        if i % 10 or not words[k]:
            continue
        scores = []
        for d, c in words.items():
            s = sum(math.log(1 + (len(words) - df[w] + 0.5) / (df[w] + 0.5)) * c[w] * 2.2 / (c[w] + 1.2 * (0.25 + 0.75 * sum(c.values()) / mean)) for w in words[k] if w in c)
            scores += [(-round(s, 6), rows[d][0])] if s else []
        want = sorted(scores)[:5]
        assert [(d, s) for _, d, s in sorted(got[i])] == [(d, pytest.approx(-s, abs=2e-6)) for s, d in want]


def test_search_frequencies_sum_over_shards(spark):
    """A row per term with the documents of all shards, so the join with the queries' terms grows with terms, not with shards."""
    frame = spark.createDataFrame([(k, f"all {k % 2} t{k}") for k in range(40)], "doc_id long, text string").repartition(8)
    index = search.build_index(frame)
    assert index.count() == 8
    assert Counter(r["df"] for r in search.frequencies(index).collect()) == {40: 1, 20: 2, 1: 40}


def test_search_skips_documents_that_only_their_block_would_open():
    """Neighbours that hold a query's rare words apart are not scored; common words (block maxima) and a query without a threshold give the same hits."""
    rng = random.Random(4)
    common_words = [f"c{k}" for k in range(6)]
    texts = [" ".join([f"w{k % 4}", *rng.sample(common_words, 3)]) if k < 16 else " ".join(rng.sample(common_words, 3) + [f"x{k}"]) for k in range(400)]
    texts[200] = "w0 w1 w2 w3 " + " ".join(common_words[:3])
    rows, terms, counts, lengths = search.document_terms(pa.array(texts))
    row = search._shard([(np.arange(400), rows, terms, counts, lengths)], 0)
    shard = search.Shard({k: pa.py_buffer(v) for k, v in row.items() if isinstance(v, bytes)}, 4.0)
    _, wanted, _, _ = search.document_terms(pa.array([f"w0 w1 w2 w3 {common_words[0]} {common_words[1]}"]))
    words = {int(t): k for k, t in enumerate(wanted)}
    weights = np.where(np.isin(wanted, shard.terms[shard.common >= 0]), 0.5, 4.0)
    assert 0 < (weights == 0.5).sum() < len(weights)
    score = np.zeros(400)
    for d, t, c in zip(rows, terms, counts, strict=True):
        if int(t) in words:
            score[d] += weights[words[int(t)]] * c * 2.2 / (c + 1.2 * (0.25 + 0.75 * lengths[d] / 4.0))
    best = sorted((-round(s, 6), d) for d, s in enumerate(score) if s)[:3]
    for floor, most in ((-np.inf, 400), (best[0][0] * -0.9, 1)):
        queries = search.QueryBlock(np.array([7]), np.array([0, len(wanted)]), wanted, weights, 3 if floor < 0 else 1)
        queries.floor[:] = floor
        queries.start()
        assert 1 <= shard.search(queries) <= most
        found = queries.found().to_pydict()
        assert found["doc_id"] == [d for _, d in best][: queries.top] and found["score"] == pytest.approx([-s for s, _ in best][: queries.top], abs=2e-6)


def test_search_ties_copies_and_levels(spark, monkeypatch):
    """Many copies in shards of a few documents: ties go to the lesser ids, across shards and levels."""
    monkeypatch.setattr(search, "SHARD_DOCUMENTS", 7)
    monkeypatch.setattr(search, "FIRST_SHARDS", 2)
    rng = random.Random(8)
    texts = ["same words here", "same words there", *(" ".join(rng.choice("abcdefghij") for _ in range(rng.randrange(1, 12))) for _ in range(30))]
    data = [(k, texts[0 if k % 3 == 0 else rng.randrange(len(texts))]) for k in range(400)]
    rng.shuffle(data)
    frame = spark.createDataFrame(data, "doc_id long, text string").repartition(3)
    got = {}
    for r in search.search(frame, frame.where("doc_id % 20 = 0"), top=6).collect():
        got.setdefault(r["query"], []).append((r["rank"], r["doc_id"], r["score"]))
    words = {i: Counter(t.split()) for i, t in data}
    mean = sum(sum(c.values()) for c in words.values()) / len(words)
    df = Counter(w for c in words.values() for w in c)
    for i, c in words.items():
        if i % 20 == 0:
            scores = []
            for d, x in words.items():
                s = sum(math.log(1 + (400 - df[w] + 0.5) / (df[w] + 0.5)) * x[w] * 2.2 / (x[w] + 1.2 * (0.25 + 0.75 * sum(x.values()) / mean)) for w in c if w in x)
                scores += [(-round(s, 6), d)] if s else []
            assert [d for _, d, _ in sorted(got[i])] == [d for _, d in sorted(scores)[:6]]


# -- 6 ---------------------------------------------------------------------------
@pytest.mark.parametrize(("width", "percent"), [(3, 85), (5, 80)])
def test_neardup(docs, rows, width, percent):
    sets = sets_of(rows, width)
    label = {k: k for k in sets}

    def root(k):
        while label[k] != k:
            k = label[k]
        return k

    for a in sets:
        for b in sets:
            if a < b and rows[a][0] is not None and rows[b][0] is not None and (rows[a][0] == rows[b][0] or sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])):
                label[max(root(a), root(b))] = min(root(a), root(b))
    least = {}
    for k in sets:
        if rows[k][0] is not None:
            least[root(k)] = min(least.get(root(k), 1 << 60), rows[k][0])
    want = Counter((rows[k][0], len(sets[k]), least.get(root(k)), rows[k][0] is None or least[root(k)] == rows[k][0]) for k in sets)
    got = Counter((r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in neardup.link(docs, width, percent).collect())
    assert got == want
    kept = [r["doc_id"] for r in neardup.deduplicate(docs, width, percent).collect()]
    assert sorted(k for k in kept if k is not None) == sorted({i for i, *_, keep in want if keep and i is not None})


def test_neardup_family_in_runs(spark, monkeypatch):
    """A family of close copies, most of them linked only through others, in runs of a few members."""
    monkeypatch.setattr(neardup, "RUN", 16)
    rng = random.Random(2)
    base = [f"w{k}" for k in range(150)]
    rows = []
    for i in range(120):
        text = list(base)
        for _ in range(rng.randrange(1, 9)):
            text[rng.randrange(150)] = f"e{rng.randrange(10**6)}"
        rows.append((1000 - i, " ".join(text), "en", "a"))
    sets = sets_of(rows, 3)
    label = list(range(120))
    changed = True
    while changed:
        changed = False
        for a in range(120):
            for b in range(120):
                if 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b]) and label[a] != label[b]:
                    low = min(label[a], label[b])
                    label[a] = label[b] = low
                    changed = True
    least = {}
    for k in range(120):
        least[label[k]] = min(least.get(label[k], 10**9), rows[k][0])
    got = {r["doc_id"]: r["component_id"] for r in neardup.link(table(spark, rows), 3, 85).collect()}
    assert got == {rows[k][0]: least[label[k]] for k in range(120)} and len(set(least.values())) > 3


def test_sketch_estimates():
    rng = np.random.default_rng(3)
    for share in (0.95, 0.85, 0.5):
        apart = []
        for _ in range(30):
            both = rng.integers(0, 1 << 63, 1000, dtype=np.uint64)
            k = int(1000 * share)
            other = np.concatenate((both[:k], rng.integers(0, 1 << 63, 1000 - k, dtype=np.uint64)))
            x, y = neardup.odd_sketches(np.stack([neardup.minhashes(both), neardup.minhashes(other)])).view(np.uint64)
            apart.append(int(np.bitwise_count(x ^ y).sum()))
        similarity = share / (2 - share)
        flips = 2 * 130 * (1 - similarity)
        assert abs(np.mean(apart) - 256 * (1 - (1 - 2 / 512) ** flips)) < 8
        assert similarity < 0.8 or max(apart) <= neardup.sketch_limit(similarity)


def test_hot_joins(spark):
    left = spark.range(5000).select((F.col("id") % 50 * (F.col("id") % 3 > 0).cast("int")).alias("k"), "id")
    right = left.groupBy("k").agg(F.count("*").alias("members"), F.max("id").alias("top")).where("k < 40")
    for how in ("inner", "left"):
        got = common.join_hot(left, right, ["k"], 5000, how)
        assert sorted(map(tuple, got.select("k", "id", "top").collect()), key=str) == sorted(map(tuple, left.join(right.drop("members"), "k", how).select("k", "id", "top").collect()), key=str)


def test_components_of_hubs(spark):
    edges = [(0, k) for k in range(1, 1500)] + [(5000, 5000 + k) for k in range(1, 1300)] + [(1400, 5007)]
    got = {r["node"]: r["component"] for r in components.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert set(got.values()) == {0} and len(got) == 2800


def test_components(spark):
    edges = [(k, k + 1) for k in range(40)] + [(100, 101), (102, 101), (7, 7)]
    got = {r["node"]: r["component"] for r in components.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {k: 0 for k in range(41)} | {100: 100, 101: 100, 102: 100}


# -- 7 ---------------------------------------------------------------------------
def labelled(spark, n=400):
    rng = random.Random(4)
    words = ["bala", "keto", "mira", "sonu", "tave"]
    rows, labels = [], []
    for i in range(n):
        bad = i % 4 == 0
        text = [rng.choice(words) + rng.choice(words) for _ in range(rng.randrange(20, 80))]
        if bad:
            for _ in range(6):
                text[rng.randrange(len(text))] = rng.choice(["gruntig", "gruntol", "vilex"])
        rows.append((i, " ".join(text), "en", "a"))
        labels.append((i, 1, int(bad)))
    return rows, spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_toxicity(spark, docs):
    rows, labels = labelled(spark)
    data = table(spark, rows)
    field = toxicity.fit_from_labels(data, labels)
    got = {r["doc_id"]: r for r in toxicity.score_documents(data, field).collect()}
    right = sum((got[i]["score"] >= 0.3) == (i % 4 == 0) for i, *_ in rows)
    assert right >= 0.97 * len(rows)
    text = dict((i, t) for i, t, _, _ in rows)
    marked = [text[0][s["start"] : s["end"]] for s in got[0]["spans"]]
    assert marked and all(re.match("grunt|vilex", m) for m in marked)
    odd = toxicity.score_documents(docs, field).collect()
    assert len(odd) == docs.count() and all(0 <= r["score"] <= 1 for r in odd)
    assert toxicity.keep_clean(data, field).count() == sum(got[i]["score"] < 0.3 for i, *_ in rows)
    unlabelled = toxicity.fit_from_labels(data, labels.limit(0))
    assert {r["score"] for r in toxicity.score_documents(docs, unlabelled).collect()} == {0.0}


def test_field_learns_from_the_last_windows():
    dense = " ".join("gruntig" if k % 14 == 0 else f"w{k % 10}" for k in range(20_000))
    late = " ".join("vilex" if k % 20 == 0 else f"w{k % 10}" for k in range(100))
    clean = " ".join(f"w{k % 10}" for k in range(20_000))
    field = toxicity.fit([clean] * 15 + [dense] * 15 + [late] * 20, [0] * 15 + [1] * 35, 0.5)
    data = np.frombuffer(b"vilex", np.uint8)
    assert field.evidence(toxicity.prefix_buckets(data, np.array([0]), np.array([5])))[0] > 1


def test_field_batches_agree(monkeypatch):
    texts = [" ".join("gruntig" if k % (13 + d) == 5 and d % 2 else f"w{k % 10}" for k in range(200)) for d in range(40)]
    whole = toxicity.fit(texts, [d % 2 for d in range(40)], 0.5)
    monkeypatch.setattr(toxicity, "BATCH", 7)
    parts = toxicity.fit(texts, [d % 2 for d in range(40)], 0.5)
    assert np.allclose(whole.weights, parts.weights, atol=1e-4) and np.allclose(whole.link, parts.link, atol=1e-3)


def test_field_marginals_against_enumeration():
    rng = np.random.default_rng(1)
    field = toxicity.Field(np.zeros(4), -1.3, rng.normal(size=(2, 2)), np.zeros(5))
    n, at, score = 7, np.array([1, 2, 5]), rng.normal(size=3)
    evidence = np.full(n, field.bias)
    evidence[at] += score
    total, hit = 0.0, np.zeros(n)
    for mask in range(1 << n):
        y = [(mask >> k) & 1 for k in range(n)]
        p = math.exp(sum(evidence[k] * y[k] for k in range(n)) + sum(field.trans[a, b] for a, b in zip([0, *y], y, strict=False)))
        total += p
        hit += p * np.array(y)
    got = field.marginals(at, score, np.zeros(3, int), np.array([n]))
    assert np.allclose(got, (hit / total)[at])


# -- 8 ---------------------------------------------------------------------------
def brute_spans(text):
    found = [("email", m.start(), m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text)]
    found += [("ip", m.start(), m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text) if all(int(p) <= 255 for p in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = re.sub("[ -]", "", m[0])
        odd = sum(int(x) for x in d[-1::-2]) + sum(sum(divmod(2 * int(x), 10)) for x in d[-2::-2])
        found += [("card", m.start(), m.end())] if 14 <= len(d) <= 19 and odd % 10 == 0 else []
    found += [("phone", m.start(), m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text) if 10 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
    return sorted(found, key=lambda s: (s[1], pii.KINDS.index(s[0])))


def test_pii_base_against_patterns():
    rng = random.Random(2)
    for _ in range(4000):
        text = "".join(rng.choice(["a", "b.", "@", ".", "1", "23", "255", "-", "+1", "(", ") ", " ", "4111 1111", "x%", "é"]) for _ in range(rng.randrange(25)))
        assert pii.base_spans(text) == brute_spans(text), text
    pii.base_spans("a" * 200_000 + "@" + "1" * 200_000 + ".1" * 100_000)


def test_pii(spark, docs, rows):
    texts = [f"word mail bob{k}@mail{k % 9}.example.com and 10.1.2.{k} or +1 (543) 555-01{k:02d} end" for k in range(60)]
    texts += [f'name token = "{hashlib.sha1(str(k).encode()).hexdigest()}" more {k * 37} x {10**9 + k}' for k in range(60)]
    data = table(spark, [(k, t, "en", "a") for k, t in enumerate(texts)])
    model = pii.fit_from_documents(data)
    got = {r["doc_id"]: r for r in pii.detect(data, model, redacted=True).collect()}
    for k, t in enumerate(texts):
        base = brute_spans(t)
        assert got[k]["base_sha256"] == hashlib.sha256(",".join(f"{a}:{b}:{c}" for a, b, c in base).encode()).hexdigest()
        assert set(filter(None, got[k]["spans"].split(","))) >= {f"{a}:{b}:{c}" for a, b, c in base}
    assert sum("secret" in got[k]["spans"] for k in range(60, 120)) >= 55
    assert "@" not in got[3]["redacted"] and "[EMAIL]" in got[3]["redacted"]
    odd = pii.detect(docs, model).collect()
    assert len(odd) == len(rows)
    assert pii.redact_documents(docs, model).columns == docs.columns and pii.redact_documents(docs, model).count() == len(rows)
    assert pii.fit_from_documents(docs.limit(0)) is None


def test_long_secrets_and_secrets_that_hold_other_spans(spark):
    rng = random.Random(3)
    hexes = lambda n: "".join(rng.choice("0123456789abcdef") for _ in range(n))
    texts = [f"word mail bob{k}@mail{k % 9}.example.com and 10.1.2.{k} or +1 (543) 555-01{k:02d} end plain_{k}_identifier_name" for k in range(60)]
    texts += [f'name token = "{hexes(rng.choice([32, 40, 64]))}" more {k * 37} x {10**9 + k}' for k in range(60)]
    model = pii.fit(texts)
    card = "4111-1111-1111-1111"
    assert ("card", 0, 19) in pii.base_spans(card)
    for secret in (hexes(129), hexes(3000), f"{hexes(20)}-{card}-{hexes(20)}", "eyJ" + hexes(400)):
        text = f'name token = "{secret}" more'
        clean = pii.redact(text, pii.find(text, model)[1])
        assert secret[:12] not in clean and secret[-12:] not in clean and clean.startswith('name token = "[') and clean.endswith(']" more')
    assert pii.redact("ab 12345 cd", [("secret", 3, 6), ("card", 5, 8)]) == "ab [SECRET] cd"
    assert pii.candidates("a" * 2_000_000 + "1") == [("secret", 0, 2_000_001)]


def private_texts(number, seed):
    rng = random.Random(seed)
    out = []
    for k in range(number):
        card = "".join(str(rng.randrange(10)) for _ in range(15))
        card = next(card + str(d) for d in range(10) if pii.luhn(card + str(d)))
        words = [rng.choice(["alpha", "ober", "linien", "quer", "mitte", "tone"]) for _ in range(30)]
        words[3:3] = [f"bob{k}.x@mail{k % 9}.example.com", "mitte", card, "tone", f"{rng.randrange(256)}.{rng.randrange(256)}.1.{k % 256}", "ober", f"+1 ({200 + k % 700}) 555-{rng.randrange(10**4):04d}"]
        words[20:20] = ['token = "' + "".join(rng.choice("0123456789abcdef") for _ in range(40)) + '"']
        out.append(" ".join(words))
    return out


def test_pii_added_spans_on_unseen_texts():
    """Loosely written data in texts that the model has not seen: precision and recall of each kind."""
    model = pii.fit(private_texts(250, 1))
    right, wrong, missed = Counter(), Counter(), Counter()
    for text in private_texts(80, 2):
        rows, labels = pii.examples(text)
        for x, y, p in zip(rows, labels, model.probability(np.array(rows, float)), strict=True):
            kind = pii.KINDS[int(x[0])]
            (right if p >= model.thresholds[kind] and y else wrong if p >= model.thresholds[kind] else missed if y else Counter())[kind] += 1
    for kind in pii.KINDS:
        assert right[kind] >= 0.85 * (right[kind] + missed[kind]) and right[kind] >= 0.9 * (right[kind] + wrong[kind]), (kind, right, wrong, missed)
    text = "my card 4111.1111.1111.1111 or write to bob dot x at mail dot example dot com for more"
    assert {k for k, _, _ in pii.find(text, model)[1]} >= {"card", "email"}


def test_uncovered_against_brute_force():
    rng = random.Random(4)
    for _ in range(300):
        spans = [("x", a, a + rng.randrange(1, 9)) for a in (rng.randrange(12) for _ in range(rng.randrange(9)))]
        want = []
        for s in spans:
            if all(s[1] < t[1] or s[2] > t[2] for t in want):
                want.append(s)
        assert pii.uncovered(spans) == want


def test_pii_many_spans_take_linear_time():
    rng = random.Random(2)
    model = pii.fit(private_texts(100, 3))
    unit = [lambda: ".".join(str(rng.randrange(256)) for _ in range(4)), lambda: f"543 555 {rng.randrange(10**4):04d}", lambda: f"x{rng.randrange(10**12)}abcdef{rng.randrange(10**9)}"]
    seconds = []
    for number in (2500, 10_000):
        text = " ".join(rng.choice(unit)() for _ in range(number))
        start = time.process_time()
        base, every = pii.find(text, model)
        seconds.append(time.process_time() - start)
        assert len(every) >= len(base) > number / 4
    assert seconds[1] < 8 * seconds[0] + 0.5


def test_boosting():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(800, 4))
    y = (x[:, 0] > 0) ^ (x[:, 1] > 0.5)
    p = boosting.fit(x, y).probability(x)
    assert ((p > 0.5) == y).mean() > 0.97


# -- 9 ---------------------------------------------------------------------------
def test_language(spark, docs, rows):
    rng = random.Random(6)
    parts = {"aa": ["ka", "lo", "mi"], "bb": ["ße", "grü", "tz"], "cc": ["ñol", "ci", "ex"], "dd": ["eau", "ch", "vi"], "ee": ["zz", "wy", "ie"], "ff": ["qu", "hh", "oo"]}
    data = [(k, " ".join("".join(rng.choice(parts[g]) for _ in range(3)) for _ in range(rng.randrange(3, 40))), g, "a") for k in range(600) for g in [rng.choice(list(parts))]]
    frame = table(spark, data)
    book = language.fit_from_documents(frame)
    got = {r["doc_id"]: r["lang_pred"] for r in language.identify(frame, book).collect()}
    assert sum(got[i] == g for i, _, g, _ in data) >= 590
    codes = language.codewords(6)
    assert (codes[:, None] != codes[None]).sum(axis=2)[np.triu_indices(6, 1)].min() >= 5
    odd = [(r["doc_id"], r["lang_pred"], r["score"]) for r in language.identify(docs, book).collect()]
    assert len(odd) == len(rows) and all(p == "und" and s == 0 for i, p, s in odd if i in (60, 61, 62, 65))
    assert {r["lang_pred"] for r in language.identify(docs, language.fit_from_documents(docs.limit(0))).collect()} == {"und"}


# -- 10 --------------------------------------------------------------------------
def test_quality(spark, docs, rows):
    good = spark.createDataFrame([(0,), (1,), (2,), (2,)], "doc_id long")
    got = quality.resample(docs, good).collect()
    assert len(got) == len(rows)
    keys = sorted((round(r["sample_key"] * 1e9) for r in got), reverse=True)
    k = len(rows) // 2
    assert all(r["selected"] == (round(r["sample_key"] * 1e9) >= keys[k - 1]) for r in got)
    assert all(r["log_weight"] == 0 for r in got if r["n_grams"] == 0)
    assert {r["log_weight"] for r in quality.resample(docs, good.limit(0)).collect()} == {0.0}


@pytest.mark.parametrize("most", [1_000_000, 1])
def test_quality_weights_against_a_recount(docs, rows, spark, monkeypatch, most):
    """Both ways to find the targets' texts give the counts of a plain recount."""
    monkeypatch.setattr(quality, "BROADCAST_IDS", most)
    chosen = {0, 1, 2, 7, 63}
    good = spark.createDataFrame([(k,) for k in [*chosen, 2, None]], "doc_id long")

    def grams(text):
        words = [common.hash_one(re.sub("[A-Z]", lambda m: m[0].lower(), w)) for w in WORD.findall(text or "")]
        pairs = [int(common.mix64(np.array([(a * 3 + b) % 2**64], np.uint64))[0]) for a, b in zip(words, words[1:], strict=False)]
        return [x >> 48 for x in words + pairs]

    whole, target = Counter(), Counter()
    for i, t, _, _ in rows:
        whole.update(grams(t))
        if i in chosen:
            target.update(grams(t))
    weight = lambda c, g: math.log((c[g] + 1) / (sum(c.values()) + 65536))
    want = sorted((i if i is not None else -1, len(grams(t)), sum(weight(target, g) - weight(whole, g) for g in grams(t))) for i, t, _, _ in rows)
    got = sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["n_grams"], r["log_weight"]) for r in quality.resample(docs, good).collect())
    assert [x[:2] for x in got] == [x[:2] for x in want] and np.allclose([x[2] for x in got], [x[2] for x in want], atol=1e-6)


def test_largest(spark):
    values = [-(1 << 63), -5, -5, 0, 3, 1 << 40, (1 << 63) - 1]
    frame = spark.createDataFrame([(v,) for v in values], "x long")
    for k in range(1, 7):
        assert quality.largest(frame, "x", k) == sorted(values, reverse=True)[k - 1]
    assert quality.largest(frame, "x", 7) is None


def test_empty_tables(spark, none):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert mixing.assign(none).count() == mixing.mix(none).count() == 0
    assert bpe.encode_documents(none).count() == media.store_documents(none).count() == token_counts.count_sections(none).count() == 0
    assert search.search(none, none).count() == neardup.link(none).count() == neardup.deduplicate(none).count() == 0
    assert toxicity.score_documents(none, toxicity.fit_from_labels(none, labels)).count() == 0
    assert pii.detect(none, pii.fit_from_documents(none)).count() == language.identify(none, language.fit_from_documents(none)).count() == 0
    assert quality.resample(none, labels).count() == 0
