"""Secrets by fixed patterns and by character Markov models (operator 4).

Fixed patterns find assignments, access keys and long hexadecimal strings. Beyond them,
tokens of LEAST or more key characters are compared under two first-order character
models: one of random strings, one of ordinary words and identifiers. A token is a
secret (kind `random`) when the log-likelihood ratio per transition passes a cutoff.

Both models are trained from labelled samples: the positives are what the fixed patterns
find in at most MAX_SAMPLE documents (those with the smallest hash of id and text; equal rows
count once) and RANDOM strings over common key alphabets from a seeded generator; the negatives
are those documents' other words (the first LONGEST characters of each; MAX_TOKENS distinct ones by
hash) and compounds of them, and of COMMON words of code, written as identifiers. A fifth of both samples is held out and sets the cutoff: halfway from the mean
that all but FALSE_RATE of the ordinary ones keep below to the one that all but a hundredth
of the random ones pass. Scanning is one pass over whole
texts; where a token touches a fixed pattern's span, its parts outside are scored.

A null text counts as empty. Rows with equal keys stay separate rows; a null key is kept.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from termatlas.llm.spans import SPAN, SPAN_SQL, as_rows, ordered
from termatlas.llm.tables import bounded_batches

KINDS, RANDOM_KIND = ("assign", "access", "hex"), "random"
MAX_SAMPLE, MAX_TOKENS, LONGEST, RANDOM, FALSE_RATE, LEAST = 4_000, 200_000, 200, 20_000, 1e-4, 20
# fixed values: the patterns of the base kinds
ASSIGN = re.compile(r"""(?ai)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")  # a run of 24 or more starts where the leftmost run does
NAMES = ("password", "passwd", "secret", "token", "apikey", "api_key")
ALPHABET = "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789+/_=-"
TOKEN, WORD = re.compile(r"[A-Za-z0-9+/_=-]{%d,}" % LEAST), re.compile(r"[A-Za-z0-9+/_=-]{4,}")
COMMON = """account action active address admin after answer array assert async author backup balance before block buffer build button bytes cache callback
change channel check class client close cluster code color column command comment commit common config connect content context control convert copy count create
current cursor data database date debug default delete detail device digest display document download edit element email enable encode engine entry error event
example execute export factory fetch field file filter find folder format function global group handle hash header height history image import index init input
insert instance invalid item join journal json keyboard kernel label language layout length level library limit line link list load local lock login logger long
lookup manager master match memory menu message method metric minimum mobile model module monitor month mount name network next node number object offset open
option order output owner package page parameter parent parse partition path pattern payment permission picture plugin point policy position power prefix process
product profile project property protocol public query queue quick range read record reference region register release remote remove render replace report request
reset resolve resource response result return role root route sample schedule schema scope screen script search section select sequence server service session set
shape share signal simple size sort source stack start state static status stop storage stream string struct style submit switch symbol system table target task
template test text thread time title total trace track transaction transfer transform tree trigger type unit update upload user utility validate value vector version
video view visible volume warning watch weight widget width window worker wrapper write year zone the and for with from this that over fox brown jumps lazy dog""".split()
POOLS = ("0123456789abcdef", "abcdefghijklmnopqrstuvwxyz234567", ALPHABET[:36] + ALPHABET[52:62], ALPHABET[:62], ALPHABET[:64], ALPHABET[:62] + "-_", ALPHABET[26:62])


def base_spans(text: str) -> list[tuple[str, int, int]]:
    out = []
    low = text.lower()
    if any(n in low for n in NAMES):
        out += [("assign", m.start(), m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 6]
    if "AKIA" in text:
        out += [("access", m.start(), m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    out += [("hex", m.start(), m.end()) for m in HEX.finditer(text)]
    return ordered(out, KINDS)


@dataclass
class Markov:
    """Log-likelihood ratios of transitions, random over ordinary, and the cutoff of their mean."""

    ratio: np.ndarray
    cutoff: float

    def mean(self, token: str) -> float:
        codes = _codes(token)
        return float(self.ratio[codes[:-1], codes[1:]].mean()) if len(codes) > 1 else -9.0

    def secret(self, token: str) -> bool:
        return len(token) >= LEAST and self.mean(token) > self.cutoff


_PLACE = np.full(256, len(ALPHABET), np.int16)
for _i, _c in enumerate(ALPHABET):
    _PLACE[ord(_c)] = _i


def _codes(token: str) -> np.ndarray:
    return _PLACE[np.frombuffer(token.encode("latin-1", "replace"), np.uint8)]


def _log_transitions(tokens: list[str]) -> np.ndarray:
    n = len(ALPHABET) + 1
    counts = np.full((n, n), 0.5)
    for t in tokens:
        c = _codes(t)
        np.add.at(counts, (c[:-1], c[1:]), 1)
    return np.log(counts / counts.sum(axis=1, keepdims=True))


def random_strings(n: int, seed: int = 5) -> list[str]:
    rng = np.random.default_rng(seed)
    return ["".join(rng.choice(list(POOLS[i % len(POOLS)]), rng.integers(LEAST, 65))) for i in range(n)]


def identifiers(words: list[str], seed: int = 6) -> list[str]:
    """Compounds of 3 to 5 words in the usual styles of identifiers and paths."""
    rng = np.random.default_rng(seed)
    out = []
    for i in range(len(words)):
        some = [words[k] for k in rng.integers(0, len(words), rng.integers(3, 6))]
        tail = str(rng.integers(0, 3000)) if i % 4 == 0 else ""
        out.append(("_".join(some).lower(), "".join(w.title() for w in some), "-".join(some), "/".join(some), "_".join(some).upper(), "=".join(some[:2]))[i % 6] + tail)
    return out


def fit(docs: DataFrame, key: str = "doc_id", text: str = "text", most: int = MAX_SAMPLE) -> Markov:
    """The models of at most `most` documents' tokens."""
    h = F.xxhash64(key, text)
    cut = docs.select(h.alias("h")).orderBy("h").limit(most).agg(F.max("h")).first()[0]
    sample = docs.where(h <= F.lit(cut if cut is not None else 0)).select(key, text).distinct()

    def tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            words, labels, seen = [], [], set()
            for value in batch.column(0):
                t = value.as_py() or ""
                spans = base_spans(t)
                for _, a, b in spans:
                    found = (WORD.findall(t[a:b]) or [""])[-1]
                    if len(found) >= LEAST:
                        words.append(found), labels.append(1)
                rest = "".join(" " * (b - a) if i else t[a:b] for i, a, b in _pieces(t, spans))
                for w in WORD.findall(rest):
                    # words repeat a lot; a document counts one once
                    if w not in seen:
                        seen.add(w), words.append(w[:LONGEST]), labels.append(0)
            yield pa.RecordBatch.from_arrays([pa.array(words, pa.string()), pa.array(labels, pa.int32())], names=["token", "y"])

    got = sample.select(text).mapInArrow(tokens, "token string, y int")
    got = got.groupBy("token").agg(F.max("y").alias("y")).orderBy(F.xxhash64("token"), "token").limit(MAX_TOKENS).toPandas()
    bad = list(got.token[got.y == 1]) + random_strings(RANDOM)
    plain = list(got.token[got.y == 0])
    ordinary = plain + identifiers([w for w in plain if w.isalpha()]) + identifiers(COMMON * 40)
    out = [zlib.crc32(t.encode()) % 5 == 0 for t in (*bad, *ordinary)]
    kept = lambda tokens, held: [t for t, h in zip(tokens, held, strict=True) if not h]
    ratio = _log_transitions(kept(bad, out[: len(bad)])) - _log_transitions(kept(ordinary, out[len(bad) :]))
    model = Markov(ratio, 0.0)
    high = [model.mean(t) for t, h in zip(bad, out[: len(bad)], strict=True) if h]
    low = [model.mean(t) for t, h in zip(ordinary, out[len(bad) :], strict=True) if h and len(t) >= LEAST]
    below = float(np.quantile(low, 1 - FALSE_RATE))
    model.cutoff = max(below, (below + float(np.quantile(high, 0.01))) / 2)
    return model


def _pieces(text: str, spans: list[tuple[str, int, int]]) -> Iterator[tuple[int, int, int]]:
    """(inside a span, start, end) from left to right."""
    at = 0
    for _, a, b in spans:
        if a > at:
            yield 0, at, a
        if b > at:
            yield 1, max(a, at), b
            at = b
    yield 0, at, len(text)


def all_spans(text: str, base: list[tuple[str, int, int]], model: Markov) -> list[tuple[str, int, int]]:
    more = [(RANDOM_KIND, m.start(), m.end()) for taken, a, b in _pieces(text, base) if not taken for m in TOKEN.finditer(text, a, b) if model.secret(m.group())]
    return ordered(base + more, (*KINDS, RANDOM_KIND)) if more else base


def scan(docs: DataFrame, model: Markov, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, base and spans (arrays of kind, start, end) of each row."""
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            base, spans = [], []
            for value in batch.column(1):
                t = value.as_py() or ""
                b = base_spans(t)
                base.append(as_rows(b)), spans.append(as_rows(all_spans(t, b, model)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(base, pa.list_(SPAN)), pa.array(spans, pa.list_(SPAN))], names=[key, "base", "spans"])

    return bounded_batches(docs).select(key, text).mapInArrow(run, f"`{key}` {kind}, base array<{SPAN_SQL}>, spans array<{SPAN_SQL}>")


def redact(docs: DataFrame, model: Markov, text: str = "text", mark: str = "<SECRET>", length: str | None = "n_chars") -> DataFrame:
    """The rows of docs with each secret's span, or merged run of spans, replaced by the mark.

    length: a column that then holds the text's length, where the text changed.
    """
    names = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out, sizes = [], []
            for value in batch.column(names.index(text)):
                t = value.as_py()
                spans = all_spans(t, base_spans(t), model) if t else []
                out.append("".join(mark if i else t[a:b] for i, a, b in _pieces(t, spans)) if spans else t)
                sizes.append(len(out[-1]) if spans else None)
            columns = list(batch.columns)
            if length in names:
                at = names.index(length)
                columns[at] = pa.array([n if s is None else s for n, s in zip(columns[at].to_pylist(), sizes, strict=True)], columns[at].type)
            columns[names.index(text)] = pa.array(out, pa.string())
            yield pa.RecordBatch.from_arrays(columns, names=names)

    return bounded_batches(docs).mapInArrow(run, docs.schema)


def digests(found: DataFrame, kinds: tuple[str, ...], key: str = "doc_id") -> DataFrame:
    """key, n_<kind> of the base spans, base_sha256 and spans as text."""

    def line(spans: str):
        return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")

    def count(kind: str):
        return F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    return found.select(key, *map(count, kinds), F.sha2(line("base"), 256).alias("base_sha256"), line("spans").alias("spans"))


def secrets(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, base, spans."""
    return scan(docs, fit(docs, key, text), key, text)
