"""Personal data by fixed patterns and bootstrapped contexts (operator 3).

Fixed patterns find e-mail and IP addresses, card and phone numbers; these are the seeds.
One pass over whole texts keeps, of each document, its seeds and its candidates: tokens
of MIN_LENGTH or more characters with a digit (or an @) that no seed overlaps. Both come
with the lexical patterns of their place: the word on the left, the two on the left, and
the words on both sides.

Spark then scores the graph of patterns and instances in rounds, until one accepts nothing
new (ROUNDS at most): a pattern's
confidence for a kind is the weight of its instances of that kind over that of all its
instances (with PRIOR doubtful ones added); an instance's is the noisy-or of its
patterns' that have LEAST_SEEDS or more different instances of confidence 0.5 and over.
Seeds keep confidence 1. A candidate of at least ACCEPT becomes an instance, its patterns
gain weight, and the next round reaches further. Each occurrence of an accepted instance
is a span of kind `context`.

Graph rows are counts of occurrences, aggregated before any shuffle of their own, so a
very common pattern or instance costs no task its occurrences.

A null text counts as empty. Rows with equal keys stay separate rows.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from termatlas.functions.scratch import materialize
from termatlas.llm.spans import SPAN, SPAN_SQL, as_rows, ordered
from termatlas.llm.tables import bounded_batches

KINDS, CONTEXT = ("email", "ip", "card", "phone"), "context"
MIN_LENGTH, ROUNDS, PRIOR, LEAST_SEEDS, ACCEPT = 5, 20, 1.0, 3, 0.8
# fixed values: the patterns of the base kinds
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])++")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DIGITS, MARKED, TOKEN, WORDS = re.compile(r"[0-9]"), re.compile(r"[0-9@]"), re.compile(r"\S+"), re.compile(r"[^\W\d_]+")
EDGE = "\"'`.,;:!?()[]{}<>*#$%&|=+"


def emails(text: str) -> Iterator[tuple[int, int]]:
    at, free_from = text.find("@"), 0
    while at >= 0:
        start = at
        while start > free_from and text[start - 1] in LOCAL:
            start -= 1
        if start < at and (m := DOMAIN.match(text, at + 1)):
            yield start, m.end()
            free_from = m.end()
            at = text.find("@", m.end())
        else:
            at = text.find("@", at + 1)


def luhn(digits: str) -> bool:
    total = sum(map(int, digits[::-2]))
    return (total + sum(sum(divmod(2 * int(d), 10)) for d in digits[-2::-2])) % 10 == 0


def base_spans(text: str) -> list[tuple[str, int, int]]:
    out = [("email", a, b) for a, b in emails(text)]
    if DIGITS.search(text):
        out += [("ip", m.start(), m.end()) for m in IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split("."))]
        for m in CARD.finditer(text):
            if m.end() - m.start() >= 12:
                digits = m.group().replace(" ", "").replace("-", "")
                if 12 <= len(digits) <= 19 and luhn(digits):
                    out.append(("card", m.start(), m.end()))
        if "+" in text:
            out += [("phone", m.start(), m.end()) for m in PHONE.finditer(text) if 9 <= len(DIGITS.findall(m.group())) <= 15]
    return ordered(out, KINDS)


def candidates(text: str, base: list[tuple[str, int, int]]) -> Iterator[tuple[int, int]]:
    """Tokens with a digit or an @ that no base span overlaps; base is sorted by start."""
    if not DIGITS.search(text) and "@" not in text:
        return
    k, ends = 0, 0
    for m in TOKEN.finditer(text):
        a, b = m.span()
        while a < b and text[a] in EDGE:
            a += 1
        while a < b and text[b - 1] in EDGE:
            b -= 1
        if b - a < MIN_LENGTH or not MARKED.search(text, a, b):
            continue
        while k < len(base) and base[k][1] < b:
            ends = max(ends, base[k][2])
            k += 1
        if ends <= a:
            yield a, b


def contexts(text: str, start: int, end: int, reach: int = 80) -> list[str]:
    """Patterns around a span, in lower case; an edge of the text counts as the word ^ or $."""
    left = WORDS.findall(text[max(0, start - reach) : start].lower())[-2:]
    right = WORDS.findall(text[end : end + reach].lower())[:1]
    one, two, after = (left or ["^"])[-1], " ".join((["^", "^"] + left)[-2:]), (right or ["$"])[0]
    return [f"{one} _", f"{two} _", f"{one} _ {after}"]


PLACE = pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32()), ("instance", pa.string()), ("patterns", pa.list_(pa.string()))])
PLACE_SQL = "struct<kind:string,start:int,end:int,instance:string,patterns:array<string>>"


def places(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """row, key, base (spans), places (seeds and candidates with their patterns); row numbers the rows."""
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            base, found = [], []
            for value in batch.column(1):
                t = value.as_py() or ""
                spans = base_spans(t)
                base.append(as_rows(spans))
                own = [(*s, t[s[1] : s[2]]) for s in spans] + [("", a, b, t[a:b]) for a, b in candidates(t, spans)]
                found.append([{"kind": k, "start": a, "end": b, "instance": x.lower(), "patterns": contexts(t, a, b)} for k, a, b, x in own])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(base, pa.list_(SPAN)), pa.array(found, pa.list_(PLACE))], names=[key, "base", "places"])

    out = bounded_batches(docs).select(key, text).mapInArrow(run, f"`{key}` {kind}, base array<{SPAN_SQL}>, places array<{PLACE_SQL}>")
    return out.withColumn("row", F.monotonically_increasing_id())


def bootstrap(found: DataFrame, rounds: int = ROUNDS) -> tuple[DataFrame, DataFrame]:
    """Accepted instances (instance, kind, confidence) and the patterns (pattern, kind, confidence, support)."""
    seen = found.select(F.explode("places").alias("p")).select("p.kind", "p.instance", F.explode(F.array_distinct("p.patterns")).alias("pattern"))
    edges = materialize(seen.groupBy("pattern", "instance", "kind").agg(F.count("*").alias("n")), "graph")
    seeds = edges.where("kind <> ''").select("instance", "kind").distinct().withColumn("confidence", F.lit(1.0))
    # only what stands in a pattern of some seed can ever be reached in a round
    known, scored, before = seeds, None, None
    total = edges.groupBy("pattern").agg(F.sum("n").alias("total"))
    for _ in range(rounds):
        weight = edges.drop("kind").join(known, "instance").groupBy("pattern", "kind").agg(F.sum(F.col("n") * F.col("confidence")).alias("w"), F.count_distinct(F.when(F.col("confidence") >= 0.5, F.col("instance"))).alias("support"))
        scored = weight.where(F.col("support") >= LEAST_SEEDS).join(total, "pattern").select("pattern", "kind", (F.col("w") / (F.col("total") + PRIOR)).alias("confidence"), "support")
        scored = materialize(scored, "patterns")
        doubt = F.sum(F.log1p(-F.least("confidence", F.lit(1 - 1e-9))))
        reached = edges.where("kind = ''").select("instance", "pattern").join(scored, "pattern").groupBy("instance", "kind").agg((-F.expm1(doubt)).alias("confidence"))
        best = reached.groupBy("instance").agg(F.max(F.struct("confidence", "kind")).alias("b")).select("instance", "b.kind", "b.confidence").where(F.col("confidence") >= ACCEPT)
        best = materialize(best.join(seeds.select("instance"), "instance", "left_anti"), "instances")
        now = tuple(best.agg(F.count("*"), F.bit_xor(F.xxhash64("instance", "kind"))).first())
        if now == before or not now[0]:
            break
        known, before = seeds.unionByName(best), now
    return best, scored


def personal(docs: DataFrame, key: str = "doc_id", text: str = "text", rounds: int = ROUNDS) -> DataFrame:
    """key, base and spans (arrays of kind, start, end) of each row."""
    found = materialize(places(docs, key, text), "places")
    best, _ = bootstrap(found, rounds)
    near = found.select("row", F.explode("places").alias("p")).where("p.kind = ''").select("row", F.col("p.start").alias("start"), F.col("p.end").alias("end"), F.col("p.instance").alias("instance"))
    more = near.join(best.select("instance"), "instance").groupBy("row").agg(F.collect_list(F.struct(F.lit(CONTEXT).alias("kind"), "start", "end")).alias("more"))
    rank = F.create_map(*(x for i, k in enumerate((*KINDS, CONTEXT)) for x in (F.lit(k), F.lit(i))))
    keyed = F.transform(F.concat("base", "more"), lambda s: F.struct(s["start"].alias("start"), rank[s["kind"]].alias("rank"), s["end"].alias("end"), s["kind"].alias("kind")))
    both = F.transform(F.array_sort(keyed), lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end")))
    return found.join(more, "row", "left").select(key, "base", F.when(F.col("more").isNull(), F.col("base")).otherwise(both).alias("spans"))
