"""The contracts' queries against brute force, on the smallest tables and on hard texts."""

import collections
import hashlib
import random
import re

import numpy as np
import pytest
import sentencepiece
from pyspark.sql import functions as F

from termatlas.llm import chat, licenses, mixing, mtree, near_dup, personal, pieces, quality, registry, secrets, toxicity

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def fuzz(alphabet, n=300, longest=60, seed=1):
    rng = random.Random(seed)
    return ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, longest))) for _ in range(n)]


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "en", "src0", 0) for i, t in enumerate(texts)], DOCS)


HARD = [None, "", " ", "\n\n", "a", "é " * 30, "word " * 3000, "x" * 20000, "▁ ▁a", "a\tb\x0bc", "日本語 テキスト", "😀 ok 😀"]


def joined(spans):
    return ",".join(f"{k}:{a}:{b}" for a, _, k, b in sorted(spans))


def brute_personal(t):
    out = [(m.start(), 0, "email", m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [(m.start(), 1, "ip", m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) <= 255 for p in m[0].split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[^0-9]", "", m[0])
        s = sum(int(c) if i % 2 == 0 else sum(map(int, str(2 * int(c)))) for i, c in enumerate(reversed(d)))
        if 12 <= len(d) <= 19 and s % 10 == 0:
            out.append((m.start(), 2, "card", m.end()))
    out += [(m.start(), 3, "phone", m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
    return joined(out)


def brute_secrets(t):
    out = [(m.start(), 0, "assign", m.end()) for m in re.finditer(r"""(?ai)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", t) if len(m[2]) >= 6]
    out += [(m.start(), 1, "access", m.end()) for m in re.finditer(r"AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
    out += [(m.start(), 2, "hex", m.end()) for m in re.finditer(r"[0-9a-f]+", t) if len(m[0]) >= 24]
    return joined(out)


def test_personal_base_patterns():
    texts = fuzz("ab1.@-_+% ", 3000) + fuzz("0123456789.- +()", 3000, seed=2) + fuzz("4 5-1", 2000, 40, seed=3) + ["a@b.c@d.e", "1.2.3.4.5.6.7.8", "001.002.003.004", "9" * 5000, "4111 1111-1111 1111", "@" * 3000, "a@" * 2000]
    for t in texts:
        assert ",".join(f"{k}:{a}:{b}" for k, a, b in personal.base_spans(t)) == brute_personal(t), t


def test_secret_base_patterns():
    texts = fuzz("toKENsecrt:='\" 0af_pi", 4000, seed=4) + fuzz("AKI0Z9f", 2000, 80, seed=5) + ["TOKEN = abcdef", "api_key:'abc'", "ſecret=abcdefg", "paſſword: 1234567", "token" + " " * 5000 + "=abcdef", "f" * 24, "F" * 24]
    for t in texts:
        assert ",".join(f"{k}:{a}:{b}" for k, a, b in secrets.base_spans(t)) == brute_secrets(t), t


@pytest.fixture(scope="module")
def texts(spark, sf):
    return {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}


def test_op3_and_op4_queries(spark, sf, texts):
    for name, brute in (("op3_personal", brute_personal), ("op4_secrets", brute_secrets)):
        rows = registry.queries()[name](spark, sf).collect()
        assert len(rows) == len(texts)
        for r in rows:
            base = brute(texts[r.doc_id])
            assert r.base_sha256 == hashlib.sha256(base.encode()).hexdigest()
            assert set(filter(None, base.split(","))) <= set(r.spans.split(","))


def test_contexts_reach_unseen_identifiers(spark):
    rng = random.Random(3)
    seeds = [f"reach me by mail {a}{i}@host{i}.example.org today" for i, a in enumerate("abcdefgh" * 3)]
    hidden = [f"reach me by mail hidden{i}x9{i} today" for i in range(4)]
    other = [f"chapter number {rng.randint(10000, 99999)} begins" for _ in range(30)]
    docs = frame(spark, seeds + hidden + other + [None, ""])
    out = {r.doc_id: [s.kind for s in r.spans] for r in personal.personal(docs).collect()}
    assert all("context" in out[len(seeds) + i] for i in range(4))
    assert all(out[len(seeds) + 4 + i] == [] for i in range(32))


def test_secret_model_and_redaction(spark):
    docs = frame(spark, ["plain words of a text with some identifiers and names in it"] * 40 + ["key ghp_16C7e42F292c6912E7710c838347Ae178B4a end", "token = abcdef123456", None, ""])
    model = secrets.fit(docs)
    assert model.secret("wJalrXUtnFEMIK7MDENGbPxRfiCYZZ") and not model.secret("get_user_account_by_identifier")
    out = {r.doc_id: r.text for r in secrets.redact(docs, model).collect()}
    assert out[40] == "key <SECRET> end" and out[41] == "<SECRET>" and out[42] is None and out[43] == "" and out[0].startswith("plain")
    key, tail = "AKIA" + "B7Q2" * 4, "wJalrXUtnFEMIK7MDENGbPxRfiCYZZ"
    both = f"{key}/{tail} end"
    base = secrets.base_spans(both)
    assert secrets.all_spans(both, base, model) == [("access", 0, 20), ("random", 20, 21 + len(tail))]
    rows = {r.doc_id: r for r in secrets.digests(secrets.scan(docs, model), secrets.KINDS).collect()}
    assert rows[41].n_assign == 1 and rows[42].spans == "" and rows[40].spans == "random:4:44"


def brute_quality(t):
    t = t or ""
    w, lines = WORDS.findall(t), [x for x in t.split("\n") if WORDS.search(x)]
    c, s = collections.Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2)), set()
    for i in range(len(w) - 2):
        if c[tuple(w[i : i + 3])] > 1:
            s |= {i, i + 1, i + 2}
    return len(w), sum(map(len, w)), sum(t.count(ch) for ch in "#*$%&|<>"), len(lines) - len(set(lines)), len(s)


def test_quality_measures(spark):
    texts = HARD + fuzz("ab \n#", 300, 80, seed=6) + fuzz("abc  \t", 100, 400, seed=7)
    rows = quality.measures(frame(spark, texts)).collect()
    assert len(rows) == len(texts)
    for r in rows:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == brute_quality(texts[r.doc_id])


def test_binomial_tails_and_certificates(spark):
    from math import comb

    for k, n, p in ((0, 10, 0.1), (3, 50, 0.05), (10, 200, 0.02), (0, 5000, 0.01), (60, 5000, 0.01)):
        want = sum(comb(n, i) * p**i * (1 - p) ** (n - i) for i in range(k + 1))
        got = spark.range(1).select(quality.binomial_tail(F.lit(k).cast("long"), F.lit(n).cast("long"), p).alias("t")).first().t
        assert abs(got - want) < 1e-9
    docs = frame(spark, [" ".join(f"w{i}x{j}" for j in range(60)) for i in range(900)] + ["# * " * 40] * 30)
    labels = spark.createDataFrame([(i, int(i < 900)) for i in range(930)], "doc_id long, quality int")
    out = quality.quality(docs, labels)
    assert out.where("doc_id < 900 and not kept").count() <= 9 and out.where("doc_id >= 900 and kept").count() == 0
    odd = docs.withColumn("lang", F.when(F.col("doc_id") % 2 == 0, F.lit("")))
    strata = quality.certify(quality.measures(odd), labels, delta=0.2).collect()
    assert sorted(str(r.lang) for r in strata) == ["", "None"]
    none = quality.quality(docs, labels.where("1 = 0"))
    assert none.where("kept = base_failed").count() == 0


def test_joint_rejections_keep_to_the_risk(spark):
    # several rules each reject another 0.5 % of the good documents: together they pass the risk
    marks = {0: "!", 1: "#"}
    rows = []
    for i in range(4000):
        words = [f"w{i}x{j}" for j in range(60)]
        if i % 200 in (0, 1):
            words = [w + marks[i % 200] * 12 for w in words]
        elif i % 200 == 2:
            words = [w.upper() + "ABCDEF" * 8 for w in words]
        elif i % 200 == 3:
            words = words[:40] + ["same old words again"] * 9
        rows.append((i, " ".join(words), "en", "s", 0))
    docs = spark.createDataFrame(rows, DOCS)
    labels = spark.range(4000).select(F.col("id").alias("doc_id"), F.lit(1).alias("quality"))
    out = quality.quality(docs, labels)
    assert out.where("not kept and not base_failed").count() <= 0.01 * 4000


def test_op2_mix(spark, sf, texts):
    rows = registry.queries()["op2_mixing"](spark, sf).collect()
    again = {r.doc_id: r.taken for r in registry.queries()["op2_mixing"](spark, sf).collect()}
    assert {r.doc_id: r.taken for r in rows} == again and len(rows) == len(texts)
    source = {r.doc_id: r.source for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    size = {i: len(WORDS.findall(t)) for i, t in texts.items()}
    total, by = sum(size.values()), collections.Counter()
    for i, n in size.items():
        by[source[i]] += n
    weight, full = {s: k % 3 + 1 for k, s in enumerate(sorted(by))}, set()
    for _ in by:  # the excess reshared until no target is above
        left = total - sum(3 * by[s] for s in full)
        goal = {s: 3 * by[s] if s in full else left * weight[s] / sum(w for t, w in weight.items() if t not in full) for s in by}
        full |= {s for s in by if goal[s] > 3 * by[s]}
    taken, largest = collections.Counter(), collections.Counter()
    for r in rows:
        s = source[r.doc_id]
        assert r.size == size[r.doc_id] and r.source_size == by[s] and abs(r.target - goal[s]) < 1e-6 and r.taken <= 3 * r.size
        taken[s] += r.taken
        largest[s] = max(largest[s], r.size)
    assert all(abs(taken[s] - goal[s]) <= largest[s] / 2 + 1 for s in by)


def test_mix_of_odd_rows(spark):
    rows = [(1, "a b c", None), (2, None, "x"), (3, "", "x"), (None, "d e", "x"), (4, "f " * 50, "y"), (4, "f " * 50, "y"), (5, "g", "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    for name in ("size", "k", "z", "s", "r", "g", "n", "copies", "unit", "_copy"):
        docs = docs.withColumn(name, F.lit(f"own {name}"))
    out, groups = mixing.mix(docs), mixing.mixed_groups(docs)
    assert out.count() == 7 and out.where("taken > 3 * size or taken is null").count() == 0
    taken = mixing.take(docs, groups)
    assert taken.columns == docs.columns and taken.count() == out.agg(F.sum("copies")).first()[0]
    assert {r.k for r in taken.collect()} == {"own k"} and {r["copies"] for r in taken.collect()} == {"own copies"}
    assert mixing.mix(docs.where("1 = 0")).count() == 0 == mixing.take(docs.where("1 = 0"), groups).count()


def test_mix_of_a_hot_group_of_equal_rows(spark):
    same = spark.range(25_000).select(F.lit(None).cast("long").alias("doc_id"), F.lit("one two three").alias("text"), F.lit("a").alias("source"))
    other = spark.range(500).select("id", F.array_join(F.array_repeat(F.lit("w"), (F.col("id") % 40 + 1).cast("int")), " ").alias("text"), F.concat(F.lit("s"), F.col("id") % 3).alias("source"))
    docs = same.union(other)
    out = mixing.mix(docs)
    by = out.groupBy("source").agg(F.first("target").alias("target"), F.sum("taken").alias("taken"), F.max("size").alias("most")).collect()
    assert out.count() == 25_500 and all(abs(r.taken - r.target) <= r.most for r in by)
    assert mixing.take(docs, mixing.mixed_groups(docs)).count() == out.agg(F.sum("copies")).first()[0]


@pytest.mark.parametrize("folder", ["sf0.01", "sf0.1"])
def test_sources_come_near_their_targets(spark, folder):
    docs = spark.read.parquet(f"/root/testdata/{folder}/documents.parquet")
    out = mixing.mix(docs).cache()
    median = out.agg(F.median("size")).first()[0]
    for r in out.groupBy("source").agg(F.first("target").alias("target"), F.sum("taken").alias("taken")).collect():
        assert abs(r.taken - r.target) <= max(0.005 * r.target, median), r
    out.unpersist()


def test_pivotal_rounding_is_unbiased(spark):
    n, runs = 400, 40
    # one of 900 words among many of 1 to 17
    units = spark.range(n).select(F.lit("s").alias("source"), F.col("id").alias("doc_id"), F.when(F.col("id") == 7, 900).otherwise(F.col("id") % 17 + 1).cast("long").alias("size"), F.lit(0).cast("long").alias("g"), F.lit(0.3).alias("p"))
    total = units.agg(F.sum("size")).first()[0]
    up = collections.Counter()
    for seed in range(6):
        out = mixing.pivotal(units.withColumn("h", F.xxhash64(F.lit(seed), "doc_id")), seed, fan=16).collect()
        assert len(out) == n and abs(sum(r.size * r.up for r in out) - 0.3 * total) <= 17
        up.update(r.doc_id for r in out if r.up)
    assert runs and abs(sum(up.values()) / (6 * n) - 0.3) < 0.03


def test_op6_learns_without_the_holdout(spark, sf):
    rows = registry.queries()["op6_toxicity"](spark, sf).collect()
    import zlib

    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and 0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in rows)


def test_toxicity_finds_the_sentence(spark):
    rng = random.Random(5)
    words = ["alpha", "beta", "gamma", "delta", "river", "stone", "house", "green"]

    def text(bad):
        s = [" ".join(rng.choices(words, k=8)) + "." for _ in range(10)]
        if bad:
            s[rng.randrange(10)] = "you are a vile zorgon indeed."
        return " ".join(s)

    docs = frame(spark, [text(i % 4 == 0) for i in range(400)] + [None, ""])
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i in range(400)] + [(9999, 1), (1, None)], "doc_id long, toxic int")
    out = {r.doc_id: r for r in toxicity.toxicity(docs, labels).collect()}
    assert all(out[i].predicted == int(i % 4 == 0) for i in range(400)) and out[400].predicted == 0 == out[401].predicted
    by_id = {r.doc_id: r.text for r in docs.collect()}
    assert all("zorgon" in by_id[i][out[i].sentences[0].start : out[i].sentences[0].end] for i in range(0, 400, 4))
    assert toxicity.clean(docs, toxicity.fit(docs, labels)).count() == 302
    assert toxicity.toxicity(docs, labels.where("1 = 0")).where("predicted = 1").count() == 0


def test_op7_against_brute_force(spark):
    rng = np.random.default_rng(4)
    rows = [(int(i), [float(x) for x in v]) for i, v in enumerate(rng.normal(size=(400, 6)) * 0.3)]
    rows += [(1000 + i, rows[0][1]) for i in range(30)] + [(2000, None), (2020, [float("nan")] * 6), (2040, [1.0, None, 0.0, 0.0, 0.0, 0.0]), (2060, [float("inf")] * 6), (20, rows[20][1])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = collections.defaultdict(list)
    for r in mtree.top_inner_products(df).orderBy("query_id", "rank").collect():
        got[r.query_id].append((r.score, r.vec_id))
    x = {i: np.floor(64 * np.array(v, np.float32).astype(float)).astype(int) for i, v in rows if v is not None and None not in v and np.isfinite(v).all()}
    ids = [i for i, v in rows if i in x]
    for q in (i for i in x if i % 20 == 0 and i != 20):
        want = sorted(((-int(x[q] @ x[i]), i) for i in ids if i != q))[:20]
        assert got[q] == [(-s, i) for s, i in want]
    assert mtree.top_inner_products(df.where("1 = 0")).count() == 0
    assert mtree.top_inner_products(df.where("vec_id in (0, 1, 2)")).count() == 2


def test_tree_pages_keep_their_bounds():
    rng = np.random.default_rng(1)
    x = rng.integers(-40, 40, (3000, 8))
    tree = mtree.Tree(np.arange(3000), x, float(np.sqrt((x**2).sum(axis=1).max())) + 1e-9)
    tree = mtree.Tree.unpack(tree.pack())
    for level in tree.levels:
        assert sorted(np.concatenate(level["pages"]).tolist()) == list(range(len(level["entries"])))
        for g, r, radius in zip(level["pages"], level["routes"], level["radii"], strict=True):
            assert (np.sqrt(((level["entries"][g] - r) ** 2).sum(axis=1)) + level["reach"][g] <= radius + 1e-9).all()
    clustered = np.vstack([rng.integers(-3, 3, (500, 8)) + c for c in rng.integers(-200, 200, (8, 8))])
    t = mtree.Tree(np.arange(4000), clustered, float(np.sqrt((clustered**2).sum(axis=1).max())) + 1e-9)
    assert min(t.search(-1, clustered[i], 5, -np.inf)[1] for i in range(0, 4000, 500)) < 3000


def brute_classes(texts):
    sets = {}
    for i, t in texts.items():
        w = WORDS.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        sets[i] = frozenset([tuple(w)] if 0 < len(w) < 5 else (tuple(w[k : k + 5]) for k in range(len(w) - 4)))
    top = {i: i for i in sets}

    def root(i):
        while top[i] != i:
            i = top[i]
        return i

    for i in sets:
        for j in sets:
            if j < i and sets[i] and 100 * len(sets[i] & sets[j]) >= 85 * len(sets[i] | sets[j]):
                a, b = root(i), root(j)
                top[max(a, b)] = min(a, b)
    return {i: (len(sets[i]), root(i)) for i in sets}


def near_texts(n=260, seed=8):
    """Families of copies at all degrees, chains, short texts and repeats."""
    rng = random.Random(seed)
    out = {0: None, 1: "", 2: "one two", 3: "ONE two", 4: "one  two", 5: "İx y z w v", 6: "i̇x y z w v"}
    base = [f"w{rng.randrange(500)}" for _ in range(60)]
    for i in range(10, n):
        w = list(base if rng.random() < 0.7 else out[rng.choice([k for k in out if k >= 10] or [2])].split())
        for _ in range(rng.randrange(4)):
            w[rng.randrange(len(w))] = f"v{rng.randrange(10000)}"
        out[i] = " ".join(w)
    return out


def test_op8_against_brute_force(spark):
    texts = near_texts()
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string").withColumn("fp", F.lit("clash"))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_dup.near_duplicates(docs).collect()}
    assert got == brute_classes(texts)
    out = near_dup.near_duplicates(docs)
    assert out.where("kept <> (doc_id = component_id)").count() == 0
    assert near_dup.near_duplicates(docs.where("1 = 0")).count() == 0
    twice = near_dup.near_duplicates(docs.unionByName(docs).unionByName(docs.limit(3).withColumn("doc_id", F.lit(None).cast("long"))))
    assert twice.count() == 2 * len(texts) + 3


def test_components_of_a_long_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(0, 60)] + [(100, 101), (101, 100), (7, 7), (None, 3)], "a long, b long")
    from termatlas.llm.components import connected_components

    got = {r.node: r.component for r in connected_components(edges).collect()}
    assert got == {**{i: 0 for i in range(61)}, 100: 100, 101: 100}
    assert connected_components(edges.where("1 = 0")).count() == 0


def test_op9_is_the_library(spark):
    import public_tokenizers

    path = public_tokenizers.path("piece_bpe_32k.model")
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    texts = HARD + fuzz("ab ▁\n\té<s>/", 400, 30, seed=9) + ["  lead", "trail ", "a" * 3000, "▁", "▁▁ ", "\x00 a"]
    out = pieces.encode_decode(frame(spark, texts), path, ("ids", "decoded", "n_tokens", "ids_sha256", "decoded_sha256")).collect()
    for r in out:
        ids = sp.encode(texts[r.doc_id] or "", add_bos=True, add_eos=True)
        assert r.ids == ids and r.n_tokens == len(ids) and r.decoded == sp.decode(ids), texts[r.doc_id]
        assert r.ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(sp.decode(ids).encode()).hexdigest()
    table = pieces.WordTable(path, words=3)
    assert all(table.encode(t or "") == sp.encode(t or "", add_bos=True, add_eos=True) for t in texts)


def test_op10_base_and_method(spark):
    texts = [None, "", "Licensed under CC-BY, cc by!", "GENERAL public  license general public license", "All Rights Reserved", "Released under the MIT License.", "permission is hereby granted free of charge to everyone", "mit license plate", "cc\nby é cc by"] + fuzz("cby al rights", 200, 40, seed=10)
    rows = {r.doc_id: r for r in licenses.digests(licenses.licenses(frame(spark, texts))).collect()}
    for i, t in enumerate(texts):
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in t or ""))
        at = [(k, label) for p, label in (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved")) for k in range(len(w)) if w[k : k + len(p.split())] == p.split()]
        r = rows[i]
        assert r.n_words == len(w) and r.n_base == len(at) and 0 <= r.score <= 1
        assert (r.first_word, r.last_word) == ((min(at)[0], max(at)[0]) if at else (None, None))
        assert r.base_labels == ",".join(sorted({x for _, x in at})) and set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(","))
    assert rows[5].labels == "mit" and rows[5].score == 1.0 and rows[7].labels == ""


def test_op10_does_not_depend_on_the_texts_length(spark):
    every = " / ".join(f"filler {k} {text} end" for k, (_, text, _) in enumerate(licenses.TEMPLATES))
    bsd = next(text for label, text, _ in licenses.TEMPLATES if label == "bsd")
    texts = [every, f"{bsd} and it is licensed under the mit license"] + ["plain words of no licence"] * 20
    rows = {r.doc_id: r for r in licenses.digests(licenses.licenses(frame(spark, texts))).collect()}
    assert set(rows[0].labels.split(",")) >= {label for label, _, _ in licenses.TEMPLATES}
    assert rows[1].labels == "bsd,mit" and rows[2].labels == ""


def test_op10_finds_what_a_search_of_all_offsets_finds():
    rng, lexicon = random.Random(11), licenses.lexicon()
    counts = {w: rng.randrange(50) for w in lexicon}
    ix, hits = licenses.index(counts=counts, total=50), 0
    for _ in range(300):
        own = []
        for _, text, _ in rng.sample(licenses.TEMPLATES, 4):
            w = text.split()
            for _ in range(rng.randrange(4)):
                w[rng.randrange(len(w))] = rng.choice(lexicon)
            own += w[rng.randrange(3) :] + rng.choices(lexicon, k=rng.randrange(5))
        at = collections.defaultdict(list)
        for i, w in enumerate(own):
            at[w].append(i)
        want = []
        for label, text, keys in licenses.TEMPLATES:
            t, best = text.split(), 0
            for offset in range(-len(t), len(own)):
                near = [" ".join(t).split(key)[0].count(" ") + offset for key in keys]
                stands = all(any(own[s : s + len(k.split())] == k.split() for s in range(max(0, p - licenses.SLACK), p + licenses.SLACK + 1)) for p, k in zip(near, keys, strict=True))
                same = sum(0 <= offset + i < len(own) and own[offset + i] == w for i, w in enumerate(t))
                if stands and same / len(t) >= licenses.LEAST_SHARE:
                    best = max(best, same / len(t))
            if best:
                want.append((label, best))
        assert [x[:2] for x in licenses.match(own, dict(at), ix)] == want
        hits += len(want)
    assert hits > 300


def test_op1_recovers_roles(spark, sf):
    c = spark.read.parquet(f"{sf}/conversations.parquet")
    p = chat.transcribe(c)
    got = chat.by_row(chat.parse(p, chat.fit(p))).join(p.select("id", "seq", "role"), ["id", "seq"])
    assert got.count() == c.count() and got.where("recovered = role").count() > 0.9 * c.count()
    one = spark.createDataFrame([(1, None, "User: hi\nthere"), (1, 0, None), (2, 5, "Bot: yes\nQ: no?")], "id long, seq long, text string")
    rows = chat.parse(one, chat.fit(p)).orderBy("id", "seq", "line").collect()
    assert len(rows) == 5 and {r.content for r in rows} == {"hi", "there", "", "yes", "no?"}
    assert "<|assistant|>\nyes\n<|end|>\n<|user|>\nno?" in chat.by_row(chat.parse(one, chat.fit(p))).where("id = 2").first().rendered


def test_op1_recovers_turns_without_a_marker(spark):
    c = spark.read.parquet("/root/testdata/sf0.01/conversations.parquet")
    p = chat.transcribe(c)
    got = chat.by_row(chat.parse(p, chat.fit(p))).join(p.select("id", "seq", "role", "text"), ["id", "seq"]).toPandas()
    bare = got[[chat.marker(chat.lines(t)[0])[0] >= chat.OTHER for t in got.text]]
    assert len(bare) >= 20 and (bare.role == bare.recovered).mean() > 0.8


def test_op1_keeps_rows_without_keys_and_equal_rows(spark, sf):
    c = spark.read.parquet(f"{sf}/conversations.parquet")
    model = chat.fit(chat.transcribe(c))
    rows = [(None, 1, "User: lost\nline"), (None, None, "Bot: also lost"), (None, 1, None), (1, 0, "User: same\nsecond"), (1, 0, "User: same\nsecond"), (1 << 60, None, "User: b"), (1 << 60, None, "Bot: a\nmore"), (1 << 60, 7, "System: c")]
    out = chat.by_row(chat.parse(spark.createDataFrame(rows, "id long, seq long, text string"), model)).collect()
    want = collections.Counter((i, s, (t or "").count("\n") + 1) for i, s, t in rows)
    assert collections.Counter((r.id, r.seq, r.n_lines) for r in out) == want
    assert sorted(r.rendered for r in out if r.id == 1) == ["<|user|>\nsame\nsecond\n<|end|>\n"] * 2
    assert {r.rendered for r in out if r.id == 1 << 60 and r.seq is None} == {"<|user|>\nb\n<|end|>\n", "<|assistant|>\na\nmore\n<|end|>\n"}
    assert {(r.recovered, r.rendered) for r in out if r.id is None and r.seq is None} == {("assistant", "<|assistant|>\nalso lost\n<|end|>\n")}


def test_op1_deals_a_common_position_into_bounded_blocks(spark):
    hot = spark.range(2000).select(F.lit(5).cast("long").alias("id"), F.when(F.col("id") < 1000, F.lit(None)).otherwise(3).cast("long").alias("seq"), F.lit("User: x").alias("text"))
    dealt = chat.dealt_rows(hot)
    assert dealt.count() == 2000 and dealt.groupBy("block").count().agg(F.max("count")).first()[0] <= chat.BLOCK
    ordered = [(r.seq is None) for r in dealt.orderBy("block", "place").collect()]
    assert ordered == sorted(ordered)


def test_blocks_of_a_transcript_join_exactly():
    rng = np.random.default_rng(2)
    model = chat.Model.of(rng.random(6) * 9, rng.random((6, 6)) * 9, rng.random((6, chat.SYMBOLS)) * 9)
    seen = rng.integers(0, chat.SYMBOLS, 40)
    whole = model.path(seen, -1, -1)
    parts, at, ends = [seen[:13], seen[13:14], seen[14:]], None, []
    for i, part in enumerate(parts):
        m = model.through(part, i == 0)
        at = m[0] if i == 0 else (at[:, None] + m).max(axis=0)
        ends.append(m)
    last = int(at.argmax())
    assert last == whole[-1]
    assert (model.path(parts[2], int(whole[13]), int(whole[-1])) == whole[14:]).all()


def test_pipeline_drops_near_copies_from_080(spark, sf):
    import corpus_pipeline

    rows = {}
    for i in range(40):
        for k, n in enumerate((55, 49, 48)):  # shared shingles over all: 46 / 56, 40 / 50, 39 / 49
            own = [f"w{i}x{n}x{j}" for j in range(n)]
            rows[1000 * k + 2 * i] = " ".join(own)
            rows[1000 * k + 2 * i + 1] = " ".join([*own[:24], "other", *own[25:]])
    docs = spark.createDataFrame([(i, t, "en", "src0", len(t)) for i, t in rows.items()], DOCS)
    kept = {r.doc_id for r in corpus_pipeline.drop_near_duplicates(spark, docs, sf).collect()}
    assert kept == {i for i in rows if i % 2 == 0 or i >= 2000}


def test_near_duplicates_of_rows_that_share_an_id(spark):
    long = " ".join(f"w{i}" for i in range(40))
    unique = " ".join(f"u{i}" for i in range(40))
    rows = [(2, long), (5, long), (5, unique), (7, long), (7, long), (8, unique + " more"), (None, long), (9, ""), (9, ""), (2, long)]
    docs = spark.createDataFrame([(i, t, "en", "s", k) for k, (i, t) in enumerate(rows)], DOCS).withColumn("stays", F.lit("own"))
    out = near_dup.drop_near_duplicates(docs)
    assert out.columns == docs.columns and {r.stays for r in out.collect()} == {"own"}
    got = sorted((str(r.doc_id), r.text) for r in out.collect())
    assert got == sorted([("2", long), ("5", unique), ("None", long), ("9", ""), ("9", "")])
    with pytest.raises(ValueError):
        near_dup.near_duplicates(docs, percent=70)


def test_long_texts_take_linear_time():
    import time

    model = secrets.Markov(np.zeros((len(secrets.ALPHABET) + 1,) * 2), 1.0)
    for text in ("7 " + "x" * 1_000_000, "a@" * 500_000, "0123456789abcdef0123456789 " * 40_000, "4 " * 500_000, "+1 " * 300_000, "token=abcdefgh " * 60_000):
        began = time.perf_counter()
        base = personal.base_spans(text)
        list(personal.candidates(text, base))
        secrets.all_spans(text, secrets.base_spans(text), model)
        assert time.perf_counter() - began < 8, text[:20]


def test_empty_tables_and_clashing_columns(spark):
    docs = frame(spark, ["plain words here and there", None]).withColumn("row", F.lit("own")).withColumn("base", F.lit("own")).withColumn("n", F.lit("own"))
    none = docs.where("1 = 0")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    runs = {
        "personal": personal.personal, "secrets": secrets.secrets, "licenses": licenses.licenses, "near": near_dup.near_duplicates, "mix": mixing.mix,
        "quality": lambda d: quality.quality(d, labels), "toxicity": lambda d: toxicity.toxicity(d, labels),
    }
    for name, run in runs.items():
        assert run(none).count() == 0, name
        assert run(docs).count() == 2, name
        assert run(docs.union(docs)).count() == 4, name
