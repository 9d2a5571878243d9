"""The experiments on the given tables, each as a DataFrame of its measures."""

from __future__ import annotations

import time
from functools import cached_property, reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from termatlas.functions.scratch import materialize
from termatlas.operators import answers, counters, exact, metrics, multicenter
from termatlas.operators import model as M
from termatlas.operators import rings as R
from termatlas.plans import methods
from termatlas.sources import adapters

#: (ratio, bands, counters) of equal space; ratio 0 is the cell model.
EQUAL_SPACE = ((0.0, 0, 216), (0.3, 5, 81), (0.4, 7, 65), (0.5, 8, 59), (0.6, 10, 50))
FREEZE = 0.2


class Bench:
    """A stream with its exact counts, band tables and reference models, each written once, when first asked for.

    times: term, times: how often each term counts in the mean errors (draws with replacement); by default once.
    messages: the messages of the arrivals with arrays of terms, of which those in `times` count; they are fewer to sort than arrivals.
    """

    def __init__(self, occ: DataFrame, candidates: int | None = None, times: DataFrame | None = None, messages: DataFrame | None = None):
        self.spark, self.candidates, self.times = occ.sparkSession, candidates, times
        self.given, self.messages = occ, messages
        self.fine = M.fine_radii()
        self._tables: dict[tuple, DataFrame] = {}

    @cached_property
    def occ(self) -> DataFrame:
        return materialize(self.given, "occ")

    @cached_property
    def counts(self) -> DataFrame:
        # arrivals that are sorted are not read anew
        return materialize(counters.counts_of_gathered(self.sorted) if "sorted" in self.__dict__ else exact.counts(self.occ), "counts")

    @cached_property
    def sorted(self) -> DataFrame:
        """The arrivals as replays take them, sorted once for all of them."""
        if self.messages is not None:
            terms = sorted(r.term for r in self.times.select("term").collect())
            codes = materialize(counters.coded_messages(self.messages, terms), "codes")
            return materialize(counters.gathered_messages(codes, terms), "sorted")
        # by way of `occ`: a sort of what is not written yet would work out places again in each of its filters
        return materialize(counters.gathered(self.occ), "sorted")

    @cached_property
    def truth(self) -> DataFrame:
        return materialize(M.fit_exact(self.counts, self.table(self.fine), self.fine, self.candidates, screen=self.screen), "truth")

    @property
    def screen(self) -> DataFrame:
        return self.table(M.fine_radii(n=M.SCREEN))

    @cached_property
    def drawn(self) -> DataFrame:
        """The reference models, each as often as its term was drawn."""
        if self.times is None:
            return self.truth
        return self.truth.join(self.times, "term").withColumn("times", F.explode(F.sequence(F.lit(1).cast("long"), "times"))).drop("times")

    def table(self, radii: list[float]) -> DataFrame:
        self.prepare([radii])
        return self._tables[tuple(radii)]

    def prepare(self, lists: list[list[float]]) -> None:
        """Write the band tables of lists of radii, all that are not there yet together, with those of the reference models."""
        wanted = dict.fromkeys(map(tuple, [*lists, self.fine, M.fine_radii(n=M.SCREEN)]))
        if fresh := [list(x) for x in wanted if x not in self._tables]:
            self._tables |= zip(map(tuple, fresh), methods.many_tables(self.spark, fresh), strict=True)

    def cells(self, capacity: int) -> methods.Atlas:
        return methods.cell_model(self.sorted, capacity, self.table(self.fine), self.fine, self.candidates, screen=self.screen)

    def rings(self, capacity: int, radii: list[float] | None = None, policy: str = "transfer", **options) -> methods.Atlas:
        radii = radii or R.edges()
        if policy == "freeze":
            options.setdefault("freeze_fraction", FREEZE)
        return methods.ring_model(self.sorted, capacity, self.table(radii), radii, policy, self.candidates, **options)


def sampled_terms(occ: DataFrame, share: float = 0.02, n: int = 1000, seed: int = 42) -> DataFrame:
    """term, times: n draws with replacement from the bag of arrivals of terms in at least this share of messages.

    Draws are points of the cumulated counts, so no arrival is collected or sorted. occ may have an array of terms a message.
    """
    heavy = materialize(counters.heavy_gathered(occ, share) if "terms" in occ.columns else counters.heavy_terms(occ, share), "heavy")
    order = Window.orderBy("term").rowsBetween(Window.unboundedPreceding, 0)
    bag = heavy.withColumn("hi", F.sum("n").over(order)).withColumn("lo", F.col("hi") - F.col("n"))
    total = bag.agg(F.max("hi").alias("total"))
    draws = occ.sparkSession.range(n).join(F.broadcast(total), F.lit(True)).select((F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 40)) / F.lit(float(1 << 40)) * F.col("total")).alias("x"))
    return F.broadcast(draws).join(bag, (F.col("x") >= F.col("lo")) & (F.col("x") < F.col("hi"))).groupBy("term").agg(F.count("*").alias("times"))


def sampled_places(counts: DataFrame, terms: int = 100, places: int = 10, seed: int = 42) -> DataFrame:
    """qid, term, cell, n: places with the term, for terms drawn by hash."""
    pick = counts.select("term").distinct().orderBy(F.xxhash64("term", F.lit(seed)), "term").limit(terms)
    order = Window.partitionBy("term").orderBy(F.xxhash64("term", "cell", F.lit(seed)), "cell")
    rows = counts.join(F.broadcast(pick), "term").withColumn("r", F.row_number().over(order)).where(F.col("r") <= places)
    return rows.select(F.xxhash64("term", "cell").alias("qid"), "term", "cell", "n")


def _tag(df: DataFrame, **values) -> DataFrame:
    return df.select(*(F.lit(v).alias(k) for k, v in values.items()), *df.columns)


def _all(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def ratio_sweep(bench: Bench, capacity: int = 50, ratios: tuple[float, ...] = (0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 2 / 3, 0.7, 0.8, 0.9)) -> DataFrame:
    """Errors of focus and spread by the ratio of neighbouring radii."""
    out, lists = [], [R.edges(ratio=r) for r in ratios]
    # counters don't depend on radii, so one replay serves all ratios
    every = materialize(R.build_each(bench.occ, capacity, lists), "summaries")
    bench.prepare(lists)
    rows = [M.ring_rows(every.where(F.col("list") == i), bench.table(radii), radii, bench.candidates).withColumn("list", F.lit(i)) for i, radii in enumerate(lists)]
    fits = materialize(M.fit(_all(rows), keep="list"), "models")
    for i, r in enumerate(ratios):
        models = M.best_center(fits.where(F.col("list") == i).drop("list"))
        out.append(_tag(metrics.relative_error(models, bench.drawn), ratio=round(r, 4), rings=R.count_for(r)))
    return _all(out)


def equal_space(bench: Bench, words: int = R.WORDS) -> DataFrame:
    """Model errors and centre accuracy for splits of the same space into counters and bands."""
    splits = [(ratio, n, m if words == R.WORDS else max(2, R.capacity_for_budget(words, n))) for ratio, n, m in EQUAL_SPACE]
    lists = [R.edges(ratio=ratio, n=n) if n else None for ratio, n, _ in splits]
    # one replay serves all splits, one fit all rings, and one the cells of counters and of the reference
    summaries = materialize(R.build_every(bench.sorted, [(m, radii) for (_, _, m), radii in zip(splits, lists, strict=True)]), "summaries")
    bench.prepare([radii for radii in lists if radii])
    own = [summaries.where(F.col("list") == i).drop("list") for i in range(len(splits))]
    rows = [M.ring_rows(own[i], bench.table(radii), radii, bench.candidates).withColumn("list", F.lit(i)) for i, radii in enumerate(lists) if radii]
    fits = materialize(M.fit(_all(rows), keep="list"), "models")
    cells = [i for i, radii in enumerate(lists) if not radii]
    sides = [(M.counts_of(own[i]), M.centres_of(own[i], bench.candidates), "cells") for i in cells]
    sides.append((bench.counts, M.top_cells(bench.counts, bench.candidates), "all"))
    *found, bench.truth = M.fit_sides(sides, bench.table(bench.fine), bench.fine, bench.screen if bench.candidates is None else None)
    models = dict(zip(cells, found, strict=True))
    out = []
    for i, (ratio, n, m) in enumerate(splits):
        got = models[i] if i in models else M.best_center(fits.where(F.col("list") == i).drop("list"))
        row = metrics.relative_error(got, bench.drawn).join(metrics.center_accuracy(got, bench.drawn), F.lit(True))
        out.append(_tag(row, ratio=ratio, rings=n, counters=m))
    return _all(out)


def frequent_recall(bench: Bench, settings: tuple[tuple[float, int], ...] = ((0.02, 50), (0.05, 20), (0.1, 10))) -> DataFrame:
    """Recall of eps-frequent places with 1 / eps counters."""
    out = []
    totals = exact.totals(bench.counts)
    for eps, m in settings:
        truth = bench.counts.join(totals, "term").where(F.col("n") >= F.lit(eps) * F.col("total"))
        found = answers.frequent_places(counters.build(bench.occ, m), eps)
        out.append(_tag(metrics.recall(found, truth), eps=eps, counters=m))
    return _all(out)


def frequency_accuracy(bench: Bench, capacity: int = 50, cell_capacity: int = 216, terms: int = 100, places: int = 10) -> DataFrame:
    """Errors of place frequencies: both models, all policies, and the model-free baselines.

    A ring summary of 50 counters and 10 bands has the space of 216 counters alone.
    """
    asked = materialize(sampled_places(bench.counts, terms, places), "asked")
    atlas = bench.cells(cell_capacity)
    out = [_tag(metrics.frequency_errors(atlas.place_frequency(asked), asked), method="cell_model")]
    out += [_tag(metrics.frequency_errors(answers.place_frequency(atlas.summary, asked, how=how), asked), method=how) for how in ("zero", "bound", "neighbours")]
    out += [_tag(metrics.frequency_errors(bench.rings(capacity, policy=p).place_frequency(asked), asked), method=f"ring_{p}") for p in R.POLICIES]
    return _all(out)


def policy_table(bench: Bench, capacity: int = 50) -> DataFrame:
    """Model errors, centre accuracy, log error of place frequencies and update time of the policies."""
    out, n = [], bench.occ.count()
    asked = materialize(sampled_places(bench.counts), "asked")
    began = time.perf_counter()
    bench.sorted  # noqa: B018
    sorting = time.perf_counter() - began
    for p in R.POLICIES:
        began = time.perf_counter()
        atlas = bench.rings(capacity, policy=p)
        # the sort is part of each update, as if each had its own
        seconds = time.perf_counter() - began + sorting
        row = metrics.relative_error(atlas.models, bench.drawn).join(metrics.center_accuracy(atlas.models, bench.drawn), F.lit(True))
        row = row.join(metrics.frequency_errors(atlas.place_frequency(asked), asked).select("log_error", "log_error_one", "pairs"), F.lit(True))
        out.append(_tag(row, policy=p, ms_an_arrival=round(1000 * seconds / max(n, 1), 4)))
    return _all(out)


def binned_pairs(occ: DataFrame, share: float = 0.02, per_bin: int = 100) -> DataFrame:
    """qid, a, b, terms, bin (1 rare .. 4 very frequent), n_places, joint, ratio: `per_bin` pairs of each bin.

    Pairs are all those of terms in at least `share` of the messages that have a place in common. The bin is the quartile of the
    joint count; equal counts share a bin. Pairs are drawn by a hash of their terms.
    """
    pairs = materialize(exact.term_pairs(occ, counters.heavy_terms(occ, share)), "pairs")
    sizes = pairs.groupBy("joint").agg(F.count("*").alias("same"))
    below = Window.orderBy("joint").rowsBetween(Window.unboundedPreceding, -1)
    place = F.floor(4 * F.coalesce(F.sum("same").over(below), F.lit(0)) / F.sum("same").over(Window.partitionBy())) + 1
    bins = sizes.select("joint", place.cast("int").alias("bin"))
    qid = F.concat_ws(" ", "a", "b")
    order = Window.partitionBy("bin").orderBy(F.md5(qid), "a", "b")
    rows = pairs.join(bins, "joint").withColumn("r", F.row_number().over(order)).where(F.col("r") <= per_bin)
    return rows.select(qid.alias("qid"), "a", "b", F.array("a", "b").alias("terms"), "bin", "n_places", "joint", "ratio")


def multi_term(occ: DataFrame, capacity: int = 10, cell_capacity: int = 43, share: float = 0.02, per_bin: int = 100) -> DataFrame:
    """Top-1 accuracy of two-term queries in four bins, by five contenders; truth is the smaller count."""
    occ = materialize(occ, "occ")
    asked = materialize(binned_pairs(occ, share, per_bin), "pairs")
    joint = exact.joint_counts(occ, asked.select("qid", "a", "b"))
    best = materialize(joint.join(joint.groupBy("qid").agg(F.max("n").alias("n")), ["qid", "n"]).select("qid", "cell"), "best")
    bins = asked.select("qid", "bin")
    used = asked.select(F.explode("terms").alias("term")).distinct()
    bench = Bench(occ.join(used, "term", "left_semi"))
    # a place without any of the terms can't be the best one; the map is cut to the data's cells
    cells = materialize(exact.counts(occ).select("cell").distinct(), "cells")
    cell, ring = bench.cells(cell_capacity), bench.rings(capacity)
    out = []
    for name, atlas in (("cell_model", cell), ("ring", ring)):
        for dep in ("independent", "bound"):
            found = atlas.hot_places_multi(asked, cells, k=1, dependence=dep)
            out.append(_tag(metrics.top_k_accuracy(found, best, bins), method=f"{name}_{dep}"))
    found = answers.intersect_summaries(ring.summary, asked, 1)
    out.append(_tag(metrics.top_k_accuracy(found, best, bins), method="intersection"))
    return _all(out)


def run_times(bench: Bench, capacity: int = 50, cell_capacity: int = 216, queries: int = 10) -> DataFrame:
    """method, update_ms (an arrival), query_s (a query with its fit), n_eval (likelihood terms a query), of each method and policy.

    A query's time starts at the summary: assembling bands (for the cell model, its cells), the fit and the answer.
    """
    n = bench.occ.count()
    asked = materialize(sampled_places(bench.counts, queries, 1), "asked")
    one = asked.count() or 1
    rows, began = [], time.perf_counter()
    occ = bench.sorted
    sorting = time.perf_counter() - began
    for name, policy in (("cell_model", None), *((f"ring_{p}", p) for p in R.POLICIES)):
        extra = {"freeze_fraction": FREEZE} if policy == "freeze" else {}
        began = time.perf_counter()
        summary = materialize(counters.build(occ, cell_capacity) if policy is None else R.build(occ, capacity, R.edges(), policy, **extra), "summary")
        built = time.perf_counter()
        # the sort is part of each update, as if each had its own
        update = built - began + sorting
        if policy is None:
            given = M.cell_rows(M.counts_of(summary), M.centres_of(summary, 1), bench.table(bench.fine), bench.fine)
        else:
            given = M.ring_rows(summary, bench.table(R.edges()), R.edges(), 1)
        given = materialize(given.join(asked.select("term").distinct(), "term", "left_semi"), "given")
        models = materialize(M.fit(given), "models")
        answers.place_frequency(summary, asked, models).count()
        done = time.perf_counter()
        evals = models.agg(F.avg("n_eval")).first()[0] or 0.0
        rows.append((name, 1000 * update / max(n, 1), (done - built) / one, float(evals)))
    return bench.spark.createDataFrame(rows, "method string, update_ms double, query_s double, n_eval double")


def replacements(bench: Bench, capacity: int = 50, slices: int = 20) -> DataFrame:
    """Share of changed top places by slice of the stream, for the first and the first three."""
    shots = materialize(R.snapshots(bench.occ, capacity, slices), "snapshots")
    return _all([_tag(metrics.replacement_curve(shots, k), top=k) for k in (1, 3)])


def stability(bench: Bench, capacity: int = 50, slices: int = 20) -> DataFrame:
    """focus_bin, spread_bin, fraction: part of the stream after which half of the centres stay."""
    rows = metrics.stable_fraction(materialize(R.snapshots(bench.occ, capacity, slices), "snapshots"), bench.truth, slices)
    return rows.groupBy(F.round("focus", 1).alias("focus_bin"), F.round("spread", 0).alias("spread_bin")).agg(F.avg("fraction").alias("fraction"), F.count("*").alias("terms"))


def maps(bench: Bench, term: str = "view", k: int = 3) -> DataFrame:
    """layer, cell, value: all places of a term, its k hottest, and its fitted surface."""
    own = bench.counts.where(F.col("term") == term)
    points = own.select(F.lit("points").alias("layer"), "cell", F.col("n").cast("double").alias("value"))
    hot = exact.hot_places(own, k).select(F.lit("hot").alias("layer"), "cell", F.col("n").cast("double").alias("value"))
    fitted = M.surface(bench.truth.where(F.col("term") == term), R.cells(bench.spark)).select(F.lit("surface").alias("layer"), "cell", F.col("est").alias("value"))
    return _all([points, hot, fitted])


def several_centres(spark: SparkSession, sf_dir: str, most: int = 3) -> DataFrame:
    """centers, error: mean absolute error of a term with two centres, by the number of fitted ones."""
    counts = materialize(exact.counts(adapters.two_centres(spark, sf_dir)), "counts")
    _, errors = multicenter.grow(counts, R.cells(spark), 0.0, most)
    return spark.createDataFrame([(k + 1, float(e)) for k, e in enumerate(errors)], "centers int, error double")


def moving(spark: SparkSession, sf_dir: str, capacity: int = 50, size: str = "7 days", slide: str = "1 day") -> DataFrame:
    """term, window_start, cell, f: the hottest place of sliding windows over a stream whose centres move east."""
    rows = counters.windowed(adapters.drifting(spark, sf_dir), capacity, size, slide)
    return rows.select("term", "window_start", F.col("centers")[0]["cell"].alias("cell"), F.col("centers")[0]["f"].alias("f"))


SHORT, MOST_SHORT = 5, 1000


def holding(docs: DataFrame, passages: DataFrame) -> DataFrame:
    """doc_id of the documents whose text contains a passage's text.

    A passage's second to fourth words stand between white space, so they are words of each text that holds it: documents and
    passages meet by these three words and `contains` confirms. Passages of fewer than SHORT words, of which there may be
    at most MOST_SHORT, are looked for in every text. Null texts hold nothing and are held by none.
    """
    docs = docs.select("doc_id", "text").where("text is not null")
    p = passages.select(F.col("text").alias("passage")).where("text is not null").distinct().withColumn("w", F.split("passage", "[ \\t-\\r]+"))
    short = p.where(F.size("w") < SHORT).select("passage")
    if (n := short.limit(MOST_SHORT + 1).count()) > MOST_SHORT:
        raise ValueError(f"over {MOST_SHORT} passages of fewer than {SHORT} words")
    key = lambda words, k: F.xxhash64(*(F.element_at(words, k + j) for j in range(3)))
    wanted = p.where(F.size("w") >= SHORT).select(key(F.col("w"), F.lit(2)).alias("key"), "passage")
    words = docs.withColumn("w", F.split("text", "[ \\t-\\r]+"))
    at = F.transform(F.sequence(F.lit(1), F.size("w") - 2), lambda k: key(F.col("w"), k))
    places = words.where(F.size("w") >= 3).select("doc_id", F.explode(F.array_distinct(at)).alias("key"))
    near = places.join(wanted, "key").select("doc_id", "passage").distinct()
    hit = near.join(docs, "doc_id").where(F.contains("text", "passage")).select("doc_id")
    if n:
        hit = hit.unionByName(docs.join(F.broadcast(short), F.contains("text", "passage")).select("doc_id"))
    return hit.distinct()
