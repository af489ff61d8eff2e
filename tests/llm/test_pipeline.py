"""The pipeline's stages on a small corpus, each against brute force on what its predecessor kept."""

from __future__ import annotations

import base64
import random
import re
from collections import Counter

import pytest
import tiktoken

import corpus_pipeline
import public_tokenizers
from gridsparse.llm import bpe, pii

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.fixture(scope="module")
def corpus(spark, tmp_path_factory):
    rng = random.Random(8)
    words = ["bala", "keto", "mira", "sonu", "tave", "rilo"]
    rows, labels = [], []
    for i in range(300):
        text = [rng.choice(words) + rng.choice(words) + str(rng.randrange(50)) for _ in range(rng.randrange(10, 60))]
        if i % 5 == 0:
            for _ in range(5):
                text[rng.randrange(len(text))] = rng.choice(["gruntig", "gruntol", "vilex"])
        if i % 7 == 1:
            text.insert(3, f"name{i}@mail{i % 9}.example.com")
            text.insert(6, f'token = "{rng.randrange(16**32):032x}"')
        rows.append((i, " ".join(text), rng.choice(["en", "de"]), rng.choice(["a", "b", "c", None])))
        labels.append((i, 1, int(i % 5 == 0)))
    for i in range(300, 340):
        text = rows[rng.randrange(300)][1].split(" ")
        if i % 2:
            text[rng.randrange(len(text))] = "changed"
        rows.append((i, " ".join(text), "en", "a"))
    rows += [(340, None, "en", "a"), (341, "", None, "b"), (342, "one two", "en", "c"), (8, rows[8][1], rows[8][2], rows[8][3])]
    folder = tmp_path_factory.mktemp("corpus")
    spark.createDataFrame([(*r, len(r[1]) if r[1] is not None else None) for r in rows], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return str(folder)


@pytest.fixture(scope="module")
def stages(spark, corpus, tmp_path_factory):
    out, folder = [spark.read.parquet(f"{corpus}/documents.parquet")], tmp_path_factory.mktemp("stages")
    for k, (_, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, out[-1], corpus).write.parquet(f"{folder}/{k}")
        out.append(spark.read.parquet(f"{folder}/{k}"))
    return out


def test_columns(stages):
    assert [name for name, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "personal_data", "mixing", "byte_bpe"]
    assert all(s.columns == COLUMNS for s in stages[:-1])


def test_toxic_documents_go(stages):
    before, after = ({r["doc_id"]: r["text"] for r in s.collect()} for s in stages[:2])
    bad = {i for i, t in before.items() if t and re.search("grunt|vilex", t)}
    assert len(bad & set(after)) <= 2 and len(set(before) - bad - set(after)) <= 2


def test_one_of_each_group_stays(stages):
    rows = [r for r in stages[1].collect()]
    sets, root = {}, {}
    for r in rows:
        w = WORD.findall((r["text"] or "").lower())
        sets[r["doc_id"]] = {tuple(w[k : k + 5]) for k in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
        root[r["doc_id"]] = r["doc_id"]

    def find(x):
        return x if root[x] == x else find(root[x])

    for a in sets:
        for b in sets:
            if a < b and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                root[max(find(a), find(b))] = min(find(a), find(b))
    assert sorted(r["doc_id"] for r in stages[2].collect()) == sorted(i for i in root if find(i) == i)


def test_personal_data_is_replaced(spark, stages, corpus):
    before, after = ({r["doc_id"]: r for r in s.collect()} for s in stages[2:4])
    assert set(before) == set(after)
    for i, r in after.items():
        text = before[i]["text"]
        base = pii.base_spans(text) if text else []
        assert not base or all(text[a:b] not in r["text"] for _, a, b in base)
        assert r["n_chars"] == (None if r["text"] is None else len(r["text"]))
        assert text is None or base or "token" in text or r["text"] == text


def test_mix_takes_whole_documents(stages):
    before, after = stages[3].collect(), Counter((r["doc_id"], r["text"]) for r in stages[4].collect())
    size, taken = Counter(), Counter()
    for r in before:
        n = len(WORD.findall(r["text"] or ""))
        size[r["source"]] += n
        taken[r["source"]] += n * after[r["doc_id"], r["text"]]
    assert max(after.values()) <= 2
    assert abs(sum(taken.values()) - 1.5 * sum(size.values())) <= 4 * 70


def test_tokens(stages):
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(public_tokenizers.path(bpe.VOCABULARY), "rb"))}
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    want = Counter((r["doc_id"], tuple(library.encode_ordinary(r["text"] or ""))) for r in stages[4].collect())
    assert Counter((r["doc_id"], tuple(r["ids"])) for r in stages[5].collect()) == want


def test_run_repeats(spark, corpus, stages):
    got = Counter((r["doc_id"], r["ids_sha256"]) for r in corpus_pipeline.run(spark, corpus).collect())
    assert got == Counter((r["doc_id"], r["ids_sha256"]) for r in stages[5].collect())


def test_mix_is_written_by_shard_and_in_its_order(spark, corpus, tmp_path):
    docs = spark.read.parquet(f"{corpus}/documents.parquet")
    shards = {}
    for r in corpus_pipeline.mixing.mix(docs).collect():
        shards.setdefault(r["mix_shard"], []).append((r["mix_order"], r["doc_id"]))
    corpus_pipeline.mix_sources(spark, docs, corpus).write.parquet(f"{tmp_path}/mix")
    files = [[r["doc_id"] for r in spark.read.parquet(str(f)).coalesce(1).collect()] for f in (tmp_path / "mix").glob("*.parquet")]
    assert sorted(f for f in files if f) == sorted([i for _, i in sorted(rows)] for rows in shards.values())
