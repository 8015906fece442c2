"""Mixing sources to target weights by entropy balancing, in DataFrame expressions only.

The mix minimises the (bounded) relative entropy between the documents' rates and one, subject to one token constraint per
source. With copies limited to `cap`, the optimum tilts the odds of a copy exponentially in the document's size: a document of
`size` words of source s is taken at rate cap / (1 + (cap - 1) e^(-t_s size)), t_s the source's dual variable. The dual is
convex; Newton rounds solve it. A round is one distributed aggregation over the histogram of sizes, which gives gradient and
curvature of all sources side by side; terms are added up as whole numbers, so that reruns agree to the last bit.

Rates become whole copies by error diffusion over a size histogram of each source, largest sizes first: each bin takes
the whole number of copies that brings the running token error nearest to zero. The histogram has at most about 9,000
bins a source whatever the number of documents (sizes up to `EXACT` exactly, then geometric bins). Within a bin, the
documents that get one copy more are the first by hash; ranks are formed in slices of about `SLICE` rows, so no bin meets in
one task.

Defined results: a null text has size 0 and takes 0 words; a null source is a source of its own, last in order; rows
that repeat a doc_id are documents of their own; an empty table gives an empty result. Where all sizes are 0, all targets are 0.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from .common import maybe_broadcast, stash

WEIGHTS = (5.0, 2.0, 1.0)
EXACT, FINE, SLICE = 2048, 512, 1000
#: Newton rounds of one job, and jobs at most; a source whose tokens are within TOLERANCE of its target is done.
ROUNDS, JOBS, TOLERANCE = 4, 16, 1e-7
#: Bins that are diffused at a time.
CHUNK = 128


def word_count(text: Column) -> Column:
    """Number of words ``[^\\x20\\x09-\\x0D]+``; null gives 0."""
    return F.coalesce(F.regexp_count(text, F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def _bin(size: Column) -> Column:
    return F.when(size <= EXACT, size).otherwise((F.lit(float(EXACT)) + F.floor(F.log(size / F.lit(float(EXACT))) * FINE)).cast("long"))


def source_targets(totals: DataFrame, weights=WEIGHTS, cap: float = 3.0) -> DataFrame:
    """(_k, _total, _target) from (_k, _source, _total): weights repeat in order of source, null last; no target above cap * total.

    Sharing the excess by weight among the rest, again and again, ends where every target is min(cap * total, weight *
    level); sorting by cap * total / weight finds the level in one pass.
    """
    order = Window.orderBy(F.col("_source").asc_nulls_last())
    table = F.array(*[F.lit(float(w)) for w in weights])
    t = totals.withColumn("_w", F.element_at(table, (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int")))
    t = t.withColumn("_ratio", cap * F.col("_total") / F.col("_w"))
    rise = Window.orderBy("_ratio", F.col("_source").asc_nulls_last())
    before = rise.rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    t = t.withColumns({
        "_all": F.sum("_total").over(every),
        "_full": F.coalesce(F.sum(cap * F.col("_total")).over(before), F.lit(0.0)),
        "_left": F.sum("_w").over(rise.rowsBetween(Window.currentRow, Window.unboundedFollowing)),
    })
    # The level is that of the first source, in this order, that stays below its limit.
    t = t.withColumn("_level", (F.col("_all") - F.col("_full")) / F.col("_left"))
    whole = rise.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    t = t.withColumn("_level", F.first(F.when(F.col("_ratio") > F.col("_level"), F.col("_level")), ignorenulls=True).over(whole))
    limit = cap * F.col("_total")
    return t.select("_k", "_total", F.least(limit, F.coalesce(F.col("_w") * F.col("_level"), limit)).alias("_target"))


def tilted_rate(x: str, cap: float) -> str:
    """SQL of the copies of a document whose odds are tilted by e^x; 1 where x is 0."""
    return f"({cap}D / (1D + ({cap}D - 1D) * exp(-greatest(-700D, least({x}, 700D)))))"


def _whole(x: str) -> Column:
    """Sum in thousandths as whole numbers, so that it does not depend on the order of rows."""
    return F.expr(f"cast(sum(cast(round({x} * 1024D) as decimal(38, 0))) as double) / 1024D")


def newton_round(hist: DataFrame, state: DataFrame, cap: float) -> DataFrame:
    """One step of every source: gradient and curvature of its dual from the histogram (_k, _size, _n), then the next tilt.

    The state holds, per source, its tilt `_u` in units of 1 / `_scale`, the bracket (`_lo`, `_hi`; null: open) and the token error.
    """
    rate = tilted_rate("_u * _size / _scale", cap)
    keys = ["_k", "_total", "_target", "_scale", "_u", "_lo", "_hi"]
    sums = hist.join(state.select(keys), "_k").groupBy(keys).agg(
        _whole(f"_n * _size * {rate}").alias("_tokens"), _whole(f"_n * _size * (_size / _scale) * {rate} * (1D - {rate} / {cap}D)").alias("_curve"),
    )
    # A step is no longer than four times the tilt, or 4; one that leaves the bracket halves it instead.
    rows = sums.selectExpr("*", "_tokens - _target as _error", "4D * greatest(1D, abs(_u)) as _most")
    rows = rows.selectExpr(
        "_k", "_total", "_target", "_scale", "_u", "_error", "if(_error < 0, _u, _lo) as _lo", "if(_error >= 0, _u, _hi) as _hi",
        "_u + greatest(-_most, least(if(_curve > 0, -_error / _curve, -signum(_error) * _most), _most)) as _there",
    )
    inside = "coalesce(_there > _lo, true) and coalesce(_there < _hi, true)"
    step = f"case when abs(_error) <= {TOLERANCE}D * _target then _u when {inside} then _there else (_lo + _hi) / 2 end as _u"
    return rows.selectExpr("_k", "_total", "_target", "_scale", step, "_lo", "_hi", "_error")


def solve_tilts(hist: DataFrame, plan: DataFrame, cap: float) -> DataFrame:
    """(_k, _total, _target, _scale, _u): the tilt of each source that is neither empty nor at its limit."""
    moments = hist.groupBy("_k").agg(F.sum(F.col("_n") * F.col("_size")).alias("_t"), F.sum((F.col("_n") * F.col("_size")).cast("decimal(38,0)") * F.col("_size")).cast("double").alias("_q"))
    state = plan.where((F.col("_target") > 0) & (F.col("_target") < cap * F.col("_total") * (1 - 1e-9))).join(moments, "_k")
    none = F.lit(None).cast("double")
    state = state.select("_k", "_total", "_target", (F.col("_q") / F.col("_t")).alias("_scale"), F.lit(0.0).alias("_u"), none.alias("_lo"), none.alias("_hi"))
    hist = maybe_broadcast(hist, 64)  # a row a source and size; Spark shuffles what is larger
    for _ in range(JOBS):
        for _ in range(ROUNDS):
            state = newton_round(hist, state, cap)
        state = stash(state, "tilts")
        worst = state.agg(F.max(F.abs("_error") / F.col("_target"))).first()[0]
        if worst is None or worst <= TOLERANCE:
            break
    return state.select("_k", "_scale", "_u")


def _let(value: Column, body) -> Column:
    """body(value), with value worked out once."""
    return F.transform(F.array(value), body)[0]


def _diffuse(bins: Column, cap: float) -> Column:
    """Copies of each bin, largest sizes first, carrying the token error on to the next bin.

    Of the two whole numbers around the wanted copies, the one whose error the smaller documents can still make up for.
    """

    def step(s: Column, b: Column) -> Column:
        known = F.struct((b["_sum"] / b["_n"]).alias("mean"), (s["err"] + b["_want"]).alias("want"), (s["rest"] - b["_sum"]).alias("rest"), (s["later"] - b["_want"]).alias("later"))

        def choose(x: Column) -> Column:
            within = lambda k: F.greatest(F.lit(0.0), F.least(k, cap * b["_n"]))

            def cost(k: Column) -> Column:
                """(error that stays whatever the smaller documents do, then the error itself; copies; error carried on)."""
                e = x["want"] - k * x["mean"]
                stays = F.greatest(-(e + x["later"]), F.lit(0.0)) + F.greatest(e + x["later"] - cap * x["rest"], F.lit(0.0))
                return F.struct((stays * 1e6 + F.abs(e)).alias("cost"), k.cast("long").alias("copies"), e.alias("err"))

            whole = F.floor(x["want"] / x["mean"]).cast("double")
            nothing = F.struct(F.lit(0.0).alias("cost"), F.lit(0).cast("long").alias("copies"), x["want"].alias("err"))
            best = F.when(b["_sum"] <= 0, nothing).otherwise(F.least(cost(within(whole)), cost(within(whole + 1))))
            return _let(best, lambda y: F.struct(
                y["err"].alias("err"), x["rest"].alias("rest"), x["later"].alias("later"), F.concat(s["out"], F.array(F.struct(b["_bin"].alias("_bin"), y["copies"].alias("_copies")))).alias("out"),
            ))

        return _let(known, choose)

    def portion(s: Column, chunk: Column) -> Column:
        """Chunk by chunk, so that the list of results is not copied once for every bin."""
        start = F.struct(s["err"].alias("err"), s["rest"].alias("rest"), s["later"].alias("later"), F.expr("cast(array() as array<struct<_bin:bigint,_copies:bigint>>)").alias("out"))
        return _let(F.aggregate(chunk, start, step), lambda done: F.struct(
            done["err"].alias("err"), done["rest"].alias("rest"), done["later"].alias("later"), F.concat(s["out"], F.array(done["out"])).alias("out"),
        ))

    chunks = F.transform(F.sequence(F.lit(0), F.floor((F.size(bins) - 1) / CHUNK).cast("int")), lambda c: F.slice(bins, c * CHUNK + 1, CHUNK))
    whole = F.aggregate(bins, F.lit(0).cast("long"), lambda t, b: t + b["_sum"])
    wanted = F.aggregate(bins, F.lit(0.0), lambda t, b: t + b["_want"])
    start = F.struct(F.lit(0.0).alias("err"), whole.alias("rest"), wanted.alias("later"), F.expr("cast(array() as array<array<struct<_bin:bigint,_copies:bigint>>>)").alias("out"))
    return F.flatten(F.aggregate(chunks, start, portion, lambda s: s["out"]))


def source_plan(sizes: DataFrame, weights=WEIGHTS, cap: float = 3.0) -> tuple[DataFrame, DataFrame]:
    """(histogram (_k, _size, _n), plan (_k, _total, _target)) of the table of sizes, both written to the shared folder."""
    hist = stash(sizes.groupBy("_k", "_size").agg(F.count("*").alias("_n")), "histogram")
    totals = hist.groupBy("_k").agg(F.sum(F.col("_n") * F.col("_size")).alias("_total")).withColumn("_source", F.when(F.col("_k") != "", F.expr("substring(_k, 2)")))
    return hist, stash(source_targets(totals, weights, float(cap)), "targets")


def mix(df: DataFrame, text: str = "text", ident: str = "doc_id", source: str = "source", weights=WEIGHTS, cap: int = 3, carry: bool = False) -> DataFrame:
    """One row per input row: (ident, size, source_size, target, rate, copies, taken); with `carry`, `_row` instead of ident."""
    docs = df.select(
        *([F.struct("*").alias("_row")] if carry else []),
        F.col(ident).alias("_id"), F.coalesce(F.concat(F.lit("="), F.col(source).cast("string")), F.lit("")).alias("_k"), word_count(F.col(text)).alias("_size"),
        F.xxhash64(F.col(text)).alias("_h"),
    )
    # The texts are counted once; all else reads the small table of sizes. Key `_k` stands for the source and is never null.
    sizes = stash(docs.select("_id", "_k", "_size", "_h"), "sizes")
    hist, plan = source_plan(sizes, weights, cap)
    plan = plan.join(solve_tilts(hist, plan, float(cap)), "_k", "left")
    full = F.col("_target") >= cap * F.col("_total") * (1 - 1e-9)
    rate = F.when(F.col("_total") <= 0, 0.0).when(full, F.lit(float(cap))).otherwise(F.expr(tilted_rate("_u * _size / _scale", float(cap))))
    fine = hist.join(plan, "_k").withColumns({"_rate": rate, "_bin": _bin(F.col("_size"))})
    bins = fine.groupBy("_k", "_bin").agg(F.sum("_n").alias("_n"), F.sum(F.col("_n") * F.col("_size")).alias("_sum"), _whole("_n * _size * _rate").alias("_want"))
    bins = bins.groupBy("_k").agg(F.sort_array(F.collect_list(F.struct("_bin", "_n", "_sum", "_want")), asc=False).alias("_bins"))
    bins = bins.withColumn("_out", F.explode(F.arrays_zip(F.col("_bins"), _diffuse(F.col("_bins"), float(cap)).alias("_d"))))
    bins = bins.select("_k", F.col("_out._bins._bin").alias("_bin"), F.col("_out._bins._n").alias("_n"), F.col("_out._d._copies").alias("_copies"))
    each = F.floor(F.col("_copies") / F.col("_n")).cast("long")
    bins = bins.withColumns({"_each": each, "_more": F.col("_copies") - each * F.col("_n"), "_slices": F.ceil(F.col("_n") / SLICE).cast("int")}).drop("_n", "_copies")
    bins = maybe_broadcast(stash(bins, "bins"), 64)
    plan = maybe_broadcast(stash(plan, "plan"), 128)

    def placed(rows: DataFrame) -> DataFrame:
        rows = rows.withColumn("_bin", _bin(F.col("_size"))).join(bins, ["_k", "_bin"])
        return rows.withColumn("_salt", F.pmod(F.xxhash64("_id", "_h"), F.col("_slices")).cast("int"))

    # Of each slice of a bin, how many documents get one copy more: the bin's first ones, counted through its slices.
    upto = Window.partitionBy("_k", "_bin").orderBy("_salt").rowsBetween(Window.unboundedPreceding, -1)
    slices = placed(sizes).where("_more > 0").groupBy("_k", "_bin", "_salt").agg(F.count("*").alias("_c"))
    slices = slices.select("_k", "_bin", "_salt", F.coalesce(F.sum("_c").over(upto), F.lit(0)).alias("_before"))
    place = F.row_number().over(Window.partitionBy("_k", "_bin", "_salt").orderBy(F.xxhash64("_id", "_h", F.lit(7)), "_id", "_h", "_size"))
    rows = placed(docs if carry else sizes)
    # Bins whose copies come out even need no ranks.
    even = rows.where("_more = 0").withColumn("copies", F.col("_each"))
    some = rows.where("_more > 0").withColumn("_rank", place).join(slices, ["_k", "_bin", "_salt"])
    some = some.withColumn("copies", F.col("_each") + (F.col("_before") + F.col("_rank") <= F.col("_more")).cast("long")).drop("_rank", "_before")
    return even.unionByName(some).join(plan, "_k").select(
        F.col("_row") if carry else F.col("_id").alias(ident),
        F.col("_size").alias("size"), F.col("_total").alias("source_size"), F.col("_target").alias("target"),
        rate.alias("rate"), "copies", (F.col("_size") * F.col("copies")).alias("taken"),
    )


def targets(df: DataFrame, text: str = "text", ident: str = "doc_id", source: str = "source", weights=WEIGHTS, cap: int = 3) -> DataFrame:
    """(ident, size, source_size, target) of every row: what the mix aims at."""
    sizes = stash(df.select(F.col(ident).alias("_id"), F.coalesce(F.concat(F.lit("="), F.col(source).cast("string")), F.lit("")).alias("_k"), word_count(F.col(text)).alias("_size")), "sizes")
    plan = maybe_broadcast(source_plan(sizes, weights, cap)[1], 64)
    return sizes.join(plan, "_k").select(F.col("_id").alias(ident), F.col("_size").alias("size"), F.col("_total").alias("source_size"), F.col("_target").alias("target"))


def mixed_documents(df: DataFrame, **options) -> DataFrame:
    """The mix itself: each document as often as it is taken (documents of rate zero go)."""
    return mix(df, carry=True, **options).where("copies > 0").withColumn("_c", F.explode(F.expr("sequence(1, copies)"))).select("_row.*")
