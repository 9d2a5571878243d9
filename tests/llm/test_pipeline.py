"""The pipeline stage by stage, each against brute force on its own input."""

import collections
import hashlib
import random
import re

import numpy as np
import public_tokenizers
import pytest
import sentencepiece

import corpus_pipeline
from termatlas.llm import mixing

WORDS = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    """60 clean documents of five sources, copies, near copies, repeated rows, toxic ones and secrets; with labels."""
    rng = random.Random(11)
    words = [f"{a}{b}" for a in ("ban", "cor", "del", "fen", "gor", "hal", "lim", "mor", "nas", "pel") for b in ("do", "ra", "ti", "vu", "so", "ke")]
    texts, toxic = [], set()
    for i in range(60):
        texts.append(" ".join(rng.choices(words, k=60 + i)) + ".")
    for i in range(6):
        texts.append(texts[i])
    changed = texts[50].split(" ")
    changed[55] = "changed"
    texts += [" ".join(changed), " ".join(rng.choices(words, k=70)) + " password = hunter2hunter2 and " + "0123456789abcdef" * 2, None, ""]
    for i in range(12):
        toxic.add(len(texts))
        texts.append(" ".join(rng.choices(words, k=50)) + f". You are a vile zorgon {rng.choice(words)}.")
    rows = [(i, t, "en", f"src{i % 5}", len(t or "")) for i, t in enumerate(texts)]
    rows.append(rows[3])
    out = tmp_path_factory.mktemp("sf")
    spark.createDataFrame(rows, DOCS).write.parquet(f"{out}/documents.parquet")
    spark.createDataFrame([(i, 1, int(i in toxic)) for i in range(len(texts))], "doc_id long, quality int, toxic int").write.parquet(f"{out}/labels.parquet")
    return str(out), toxic


def similar(a, b, percent=80):
    return len(a & b) * 100 >= percent * len(a | b) > 0


def shingles(text):
    w = WORDS.findall((text or "").lower())
    return frozenset([tuple(w)] if 0 < len(w) < 5 else (tuple(w[k : k + 5]) for k in range(len(w) - 4)))


def test_stages(spark, folder):
    sf, toxic = folder
    stages = dict(corpus_pipeline.STAGES)
    docs = spark.read.parquet(f"{sf}/documents.parquet").select(*(f.split()[0] for f in DOCS.split(", ")))
    names = docs.columns

    clean = stages["toxicity"](spark, docs, sf).cache()
    assert clean.columns == names
    kept = {r.doc_id for r in clean.collect()}
    assert not kept & toxic and kept == {r.doc_id for r in docs.collect()} - toxic

    single = stages["near_duplicates"](spark, clean, sf).cache()
    sets = {r.doc_id: shingles(r.text) for r in clean.collect()}
    top = {i: i for i in sets}

    def root(i):
        while top[i] != i:
            i = top[i]
        return i

    for i in sets:
        for j in sets:
            if i < j and similar(sets[i], sets[j]):
                a, b = root(i), root(j)
                top[max(a, b)] = min(a, b)
    assert sorted(r.doc_id for r in single.collect()) == sorted(i for i in sets if root(i) == i)

    hidden = stages["secrets"](spark, single, sf).cache()
    before = {r.doc_id: r.text for r in single.collect()}
    after = {r.doc_id: r for r in hidden.collect()}
    assert before.keys() == after.keys() and hidden.columns == names and 67 in after and "hunter2" in before[67]
    for i, r in after.items():
        if before[i] and "hunter2" in before[i]:
            assert "hunter2" not in r.text and "0123456789abcdef" not in r.text and "<SECRET>" in r.text and r.n_chars == len(r.text)
        else:
            assert r.text == before[i]

    mixed = stages["mixing"](spark, hidden, sf).cache()
    copies = {r.doc_id: r.copies for r in mixing.mix(hidden).collect()}
    assert mixed.columns == names
    assert collections.Counter(r.doc_id for r in mixed.collect()) == {i: n for i, n in copies.items() if n}

    encoded = stages["encoding"](spark, mixed, sf).collect()
    library = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    want = collections.Counter()
    for r in mixed.collect():
        ids = library.encode(r.text or "", add_bos=True, add_eos=True)
        want[r.doc_id, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(library.decode(ids).encode()).hexdigest()] += 1
    assert collections.Counter((r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in encoded) == want


def test_joins_of_the_mix_are_by_key(spark, folder):
    docs = spark.read.parquet(f"{folder[0]}/documents.parquet")
    plan = mixing.take(docs, mixing.mixed_groups(docs))._jdf.queryExecution().toString()
    assert "NestedLoop" not in plan and "Cartesian" not in plan
