"""Mixing sources to target weights by pivotal dependent rounding (operator 2), in DataFrame functions only.

A source's target is its share of all words by weight, at most `cap` times its size, the
excess reshared. Every document of a source is to be copied target / size times: the whole
part is certain, the fraction is a probability. Fractions are paired: words move from a document
to its partner, at random in the direction that keeps both expectations, until one of the
two is whole. The partner is the pool of all smaller documents of the block; they share what
they give or take in proportion, and are settled in turn, so a block leaves one residual, as a rule
its smallest document. Residuals of about FAN blocks meet in a block of the next level, and
so on up a tree. The few documents of a source that are larger than its LARGE-th part are settled
before all others, against all of them. So the expected copies of each document and a source's
words are kept. Only a document that all smaller ones of its source together cannot balance, such as
the very last, is rounded to the nearer integer; so a source ends within half of one document of its
target, mostly of a smallest one. No block grows with its source.

Equal rows (doc_id, source, text) are one unit of as many copies, spread evenly over them, so
a group of any size costs one row. Null and empty texts have size 0 and take no words; their
copies are drawn one by one. A null source is a source of its own, last in order; a null
doc_id is a value like others. Targets need one row per source in one task, nothing more.
Random numbers are hashes of ids, texts and the seed, so reruns agree, however rows are dealt.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from termatlas.functions.scratch import materialize

WORD, FAN, LARGE, TWO53, EXPANDED = r"[^\x20\x09-\x0D]+", 64, 256, float(1 << 53), 10_000


def _size(text: str) -> Column:
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def sizes(docs: DataFrame, key: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """doc_id, source, size (words), g (a hash of the text) of each row; keys are integers."""
    return docs.select(F.col(key).cast("long").alias("doc_id"), F.col(source).alias("source"), _size(text).alias("size"), F.xxhash64(text).alias("g"))


def targets(sized: DataFrame, weights: tuple[float, ...] = (1, 2, 3), cap: float = 3.0) -> DataFrame:
    """source, source_size, target: one row per source.

    Sources by code point, null last, take the weights in turn. Ordered by the level at which
    they reach their cap, the sources below the common level are the full ones.
    """
    by = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    ranked = Window.orderBy(F.col("source").asc_nulls_last())
    every = Window.partitionBy()
    place = (F.pmod(F.row_number().over(ranked) - 1, F.lit(len(weights))) + 1).cast("int")
    w = by.withColumn("weight", F.element_at(F.array(*(F.lit(float(x)) for x in weights)), place))
    w = w.withColumn("most", F.col("source_size") * F.lit(float(cap))).withColumn("reach", F.col("most") / F.col("weight"))
    before = Window.orderBy("reach", F.col("source").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, -1)
    w = w.withColumn("left", F.sum("source_size").over(every) - F.coalesce(F.sum("most").over(before), F.lit(0.0)))
    w = w.withColumn("level", F.col("left") / (F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))))
    first = F.min(F.when(F.col("reach") > F.col("level"), F.struct("reach", "level"))).over(every)
    goal = F.least("most", F.coalesce(first["level"] * F.col("weight"), F.col("most")))
    return w.withColumn("target", goal).select("source", "source_size", "target")


def _uniform(*of: Column) -> Column:
    return F.pmod(F.xxhash64(*of), F.lit(1 << 53)) / F.lit(TWO53)


_NAMES = ("doc_id", "size", "g")
_UNIT = "struct<order:bigint,h:bigint,doc_id:bigint,size:bigint,g:bigint,p:double>"
_DONE = "array<struct<doc_id:bigint,size:bigint,g:bigint,up:int>>"
_WHOLE = 1e-9


def _settled(units: Column, size: Column, mass: Column, seed: int, final: bool) -> Column:
    """carry, done, a, b: units in turn, largest first, each against the pool of all later ones.

    size and mass (size * p) are of the pool with the units. Words move between a unit and the
    pool until one of them is whole; a unit that the pool cannot make whole is carried. With
    `final` it is rounded instead, and the pool makes up for it as far as it can. A pool's documents share
    by what each can give or take, so their probabilities go through one line, a * p + b.
    """
    start = F.struct(
        F.lit(1.0).alias("a"), F.lit(0.0).alias("b"), size.cast("double").alias("size"), mass.alias("mass"),
        F.lit(None).cast(_UNIT).alias("carry"), F.array().cast(_DONE).alias("done"),
    )

    def step(s: Column, x: Column) -> Column:
        pool = s["size"] - x["size"]
        p = F.least(F.greatest(s["a"] * x["p"] + s["b"], F.lit(0.0)), F.lit(1.0))
        has = F.greatest(s["a"] * (s["mass"] - x["p"] * x["size"]) + s["b"] * pool, F.lit(0.0))
        facts = F.struct(p.alias("p"), pool.alias("pool"), has.alias("has"), F.greatest(pool - has, F.lit(0.0)).alias("room"))
        return _let(facts, lambda f: _let(_moves(f, x, seed, final), lambda m: _after(s, x, f, m, final)))

    return F.aggregate(units, start, step, lambda s: F.struct(s["carry"].alias("carry"), s["done"].alias("done"), s["a"].alias("a"), s["b"].alias("b")))


def _let(value: Column, use) -> Column:
    """use(value), with value computed once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _moves(f: Column, x: Column, seed: int, final: bool) -> Column:
    """Words that the pool gives if x goes up, and takes if it goes down, and which it is."""
    lacks, mass = (1 - f["p"]) * x["size"], f["p"] * x["size"]
    give, takes = F.least(lacks, f["has"]), F.least(mass, f["room"])
    up = _uniform(F.lit(seed), x["h"], x["size"]) * (give + takes) < takes
    if final:
        up = F.when((lacks <= f["has"]) & (mass <= f["room"]), up).otherwise(f["p"] >= 0.5)
    return F.struct(give.alias("give"), takes.alias("take"), up.alias("up"))


def _after(s: Column, x: Column, f: Column, m: Column, final: bool) -> Column:
    whole = (f["p"] <= _WHOLE) | (f["p"] >= 1 - _WHOLE)
    moved = F.when(m["up"], F.lit(1.0)).otherwise(0.0) if final else F.when(m["up"], f["p"] + m["give"] / x["size"]).otherwise(f["p"] - m["take"] / x["size"])
    new = F.when(whole, f["p"]).otherwise(moved)
    less = F.when(m["up"] & (f["has"] > 0), m["give"] / f["has"]).when(~m["up"] & (f["room"] > 0), m["take"] / f["room"]).otherwise(0.0)
    rest = F.when(whole, 1.0).otherwise(F.greatest(1 - less, F.lit(0.0)))
    lift = F.when(m["up"], 0.0).otherwise(1 - rest)
    ended = (new <= _WHOLE) | (new >= 1 - _WHOLE)
    carried = F.struct(*(x[n].alias(n) for n in ("order", "h", *_NAMES)), F.coalesce(new, F.lit(0.0)).alias("p"))
    decided = F.struct(*(x[n].alias(n) for n in _NAMES), F.coalesce((new > 0.5).cast("int"), F.lit(0)).alias("up"))
    return F.struct(
        (s["a"] * rest).alias("a"), (s["b"] * rest + lift).alias("b"), f["pool"].alias("size"), (s["mass"] - x["p"] * x["size"]).alias("mass"),
        F.when(ended, s["carry"]).otherwise(carried).alias("carry"),
        F.when(ended, F.concat(s["done"], F.array(decided))).otherwise(s["done"]).alias("done"),
    )


def _of_groups(units: DataFrame, by: list[str], seed: int, final: bool) -> DataFrame:
    """by, carry, done of units (by, unit)."""
    lists = units.groupBy(*by).agg(F.array_sort(F.collect_list("unit")).alias("units"), F.sum("unit.size").alias("all"), F.sum(F.col("unit.size") * F.col("unit.p")).alias("mass"))
    folded = lists.select(*by, _settled(F.col("units"), F.col("all"), F.col("mass"), seed, final).alias("s"))
    return materialize(folded.select(*by, "s.carry", "s.done"), "fold")


def _decided(folded: DataFrame) -> DataFrame:
    return folded.select("source", F.explode("done").alias("d")).select("source", "d.*")


def pivotal(units: DataFrame, seed: int, fan: int = FAN) -> DataFrame:
    """source, doc_id, size, g, up of units (source, doc_id, size, g, h, p in (0, 1)); up is 1 with probability p.

    Documents above a LARGE-th part of their source, fewer than LARGE of them, are settled against all the rest.
    The rest then goes through the tree: blocks of about `fan`, blocks of residuals, and so on.
    """
    unit = F.struct((-F.col("size")).alias("order"), "h", *_NAMES, "p").alias("unit")
    rows = units.select("source", unit)
    sums = rows.groupBy("source").agg(F.sum("unit.size").alias("all"), F.sum(F.col("unit.size") * F.col("unit.p")).alias("mass"), F.count("*").alias("n"))
    sums = materialize(sums.withColumnRenamed("source", "s"), "sums")
    most = sums.agg(F.max("n")).first()[0] or 0
    rows = rows.join(sums, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    is_large = F.col("unit.size") * LARGE > F.col("all")
    large = rows.where(is_large).groupBy("source").agg(F.array_sort(F.collect_list("unit")).alias("units"), F.first("all").alias("all"), F.first("mass").alias("mass"))
    first = materialize(large.select("source", _settled(F.col("units"), F.col("all"), F.col("mass"), seed, True).alias("s")).select("source", "s.*"), "large")
    parts = [_decided(first)]
    line = first.select(F.col("source").alias("s"), "a", "b")
    p = F.least(F.greatest(F.coalesce(F.col("a") * F.col("unit.p") + F.col("b"), F.col("unit.p")), F.lit(0.0)), F.lit(1.0))
    rest = rows.where(~is_large).join(line, F.col("source").eqNullSafe(F.col("s")), "left")
    level = rest.select("source", F.pmod(F.col("unit.h"), F.greatest(F.ceil(F.col("n") / fan), F.lit(1))).alias("block"), F.col("unit").withField("p", p).alias("unit"))
    n = max(1, -(-most // fan))
    while True:
        folded = _of_groups(level, ["source", "block"], seed + 3, n == 1)
        parts.append(_decided(folded))
        if n == 1:
            return reduce(DataFrame.unionByName, parts)
        left = folded.where("carry is not null")
        n, level = -(-n // fan), left.select("source", F.floor(F.col("block") / fan).alias("block"), F.col("carry").alias("unit"))


def mixed_groups(docs: DataFrame, weights: tuple[float, ...] = (1, 2, 3), cap: float = 3.0, seed: int = 11, key: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """doc_id, source, size, g, n (equal rows), source_size, target, copies (of all n together)."""
    sized = materialize(sizes(docs, key, source, text).groupBy("doc_id", "source", "size", "g").agg(F.count("*").alias("n")), "sizes")
    goal = materialize(targets(sized.select("source", (F.col("size") * F.col("n")).alias("size")), weights, cap), "targets")
    g = goal.withColumnRenamed("source", "s")
    want = sized.join(g, F.col("source").eqNullSafe(F.col("s"))).drop("s")
    times = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(1.0))
    want = want.withColumn("x", times * F.col("n")).withColumn("whole", F.floor("x")).withColumn("p", F.col("x") - F.col("whole"))
    want = want.withColumn("h", F.xxhash64(F.lit(seed), "doc_id", "size", "g"))
    open_ = (F.col("size") > 0) & (F.col("p") > 0)
    names = ["source", *_NAMES]
    rounded = pivotal(want.where(open_).select(*names, "h", "p"), seed).select(*(F.col(n).alias(f"_{n}") for n in names), "up")
    same = reduce(lambda a, b: a & b, (F.col(n).eqNullSafe(F.col(f"_{n}")) for n in names))
    out = want.join(rounded, same, "left").withColumn("up", F.coalesce("up", F.when(_uniform(F.lit(seed + 1), F.col("h")) < F.col("p"), 1).otherwise(0)))
    return out.select(*names, "n", "source_size", "target", (F.col("whole") + F.col("up")).cast("long").alias("copies"))


def mix(docs: DataFrame, weights: tuple[float, ...] = (1, 2, 3), cap: float = 3.0, seed: int = 11, key: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken (words) of each row."""
    groups = mixed_groups(docs, weights, cap, seed, key, source, text)
    # a group's rows are made in chunks, which are dealt apart where there are many
    chunk = F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("n") - 1) / EXPANDED)))
    rows = groups.withColumn("chunk", chunk)
    place = F.sequence(F.col("chunk") * EXPANDED, F.least(F.col("n"), (F.col("chunk") + 1) * EXPANDED) - 1)
    rows = rows.withColumn("i", F.explode(place))
    copies = F.floor(F.col("copies") / F.col("n")) + (F.col("i") < F.pmod("copies", "n")).cast("long")
    out = rows.withColumn("copies", copies.cast("int"))
    return out.select("doc_id", "source", "size", "source_size", "target", "copies", (F.col("copies") * F.col("size")).alias("taken"))


def take(docs: DataFrame, groups: DataFrame, key: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """The rows of docs, each as often as groups (of mixed_groups) say.

    Of equal rows (doc_id, source, text) all are taken equally often; what doesn't divide is taken from one of them.
    """
    own = F.struct(F.col(key).cast("long").alias("doc_id"), F.col(source).alias("source"), F.xxhash64(text).alias("g"))
    g = groups.select(
        F.struct("doc_id", "source", "g").alias("_mix_of"), F.floor(F.col("copies") / F.col("n")).cast("int").alias("_mix_each"), F.pmod("copies", "n").alias("_mix_more")
    )
    # one column of a struct, so no name of the user's is touched; hashes of nulls agree, eqNullSafe keeps them
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_mix_row"), own.alias("_mix_own"))
    same = F.col("_mix_own").eqNullSafe(F.col("_mix_of"))
    each = rows.join(g.where("_mix_each > 0"), same).select("_mix_row", F.explode(F.array_repeat(F.lit(0), F.col("_mix_each"))).alias("_mix_copy"))
    out = each.select("_mix_row.*")
    more = g.where("_mix_more > 0")
    if not more.isEmpty():
        one = rows.join(more, same, "left_semi").groupBy("_mix_own").agg(F.min("_mix_row").alias("_mix_row"))
        extra = one.join(more, same).select("_mix_row", F.explode(F.sequence(F.lit(1).cast("long"), "_mix_more")).alias("_mix_copy"))
        out = out.unionByName(extra.select("_mix_row.*"))
    return out
