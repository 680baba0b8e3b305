"""Temperature mixing of sources, with DataFrame functions only.

Source token shares p are raised to an exponent a and normalised. The exponent is bisected
so that the mixture is as close to the natural one (a = 1) as a limit allows: a wanted
entropy, or a bound on how often a source's tokens may repeat. The weights then become
numbers of copies: whole passes over a source, plus the part of one more pass that the
source's token budget leaves, taken in an order that permutes blocks of documents and the
documents inside a block.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from cubelens.storage import keep, materialize, release

#: Share of the entropy of the uniform mixture that the mixture should reach at least.
ENTROPY_SHARE = 0.9
MAX_REPEATS = 4.0
#: Expected documents in a block.
BLOCK_DOCS = 1024
#: Blocks of a source are summed up in so many ranges of their permuted order, then inside each range.
RANGE_BITS = 12
#: Halvings of the exponent's interval [0, 1].
STEPS = 50
#: Sources whose shares are bisected inside one row; more are refused (16 bytes each).
MAX_SOURCES = 1_000_000


def token_count(text: Column) -> Column:
    """Words of a text: runs of anything but space and the controls 9 to 13; null has none."""
    one = F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x20\x09-\x0D]+", " ")
    return (F.length(one) - F.length(F.replace(one, F.lit(" "))) + 1 - one.startswith(" ").cast("int") - one.endswith(" ").cast("int") - (one == "").cast("int")).cast("long")


def _powers(shares: Column, a: Column) -> Column:
    return F.transform(shares, lambda p: F.pow(p, a))


def _entropy(shares: Column, a: Column) -> Column:
    """Entropy of the shares raised to a and normalised."""
    sums = F.aggregate(_powers(shares, a), F.struct(F.lit(0.0).alias("z"), F.lit(0.0).alias("e")), lambda s, x: F.struct((s["z"] + x).alias("z"), (s["e"] + F.when(x > 0, x * F.ln(x)).otherwise(0.0)).alias("e")), lambda s: F.ln(s["z"]) - s["e"] / F.nullif(s["z"], F.lit(0.0)))
    return sums


def _repeats(shares: Column, a: Column) -> Column:
    """Largest ratio of a mixture weight to its natural share: the passes at an equal budget."""
    z = F.aggregate(_powers(shares, a), F.lit(0.0), lambda s, x: s + x)
    return F.aggregate(shares, F.lit(0.0), lambda s, p: F.greatest(s, F.pow(p, a) / p)) / F.nullif(z, F.lit(0.0))


def source_weights(tokens: DataFrame, entropy_share: float | None = ENTROPY_SHARE, max_repeats: float | None = MAX_REPEATS, budget_tokens: int | None = None) -> DataFrame:
    """(source, n_docs, tokens, share, exponent, weight, budget) for a table (source, n_tokens).

    The exponent is the largest of [0, 1] whose entropy is at least ``entropy_share`` of the
    logarithm of the number of sources; if that repeats a source's tokens more than
    ``max_repeats`` times at a budget of ``budget_tokens`` (default: all tokens), it is the
    smallest that does not (the repetition limit wins). A budget of more than ``max_repeats``
    times all tokens can't be met by any exponent: ``budget`` is cut to that many, at exponent
    1. Sources without tokens get weight 0. A null source is a source of its own.
    """
    per = tokens.groupBy("source").agg(F.count("*").alias("n_docs"), F.sum("n_tokens").alias("tokens"))
    per = materialize(per, "sources")
    if per.count() > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    total = per.agg(F.sum("tokens"))
    budget = F.coalesce(total.scalar(), F.lit(0)) if budget_tokens is None else F.lit(budget_tokens).cast("long")
    row = per.filter("tokens > 0").agg(F.array_sort(F.collect_list(F.col("tokens").cast("double"))).alias("t"))
    row = row.select("t", F.aggregate("t", F.lit(0.0), lambda s, y: s + y).alias("all"))
    row = row.select("all", F.transform("t", lambda x: x / F.col("all")).alias("p"))
    interval = F.struct(F.lit(0.0).alias("lo"), F.lit(1.0).alias("hi"))

    def bisect(keeps_low) -> Column:
        """The border in [0, 1] below which keeps_low holds."""

        def step(s: Column, _: Column) -> Column:
            mid = (s["lo"] + s["hi"]) / 2
            low = keeps_low(mid)
            return F.struct(F.when(low, mid).otherwise(s["lo"]).alias("lo"), F.when(low, s["hi"]).otherwise(mid).alias("hi"))

        return F.aggregate(F.sequence(F.lit(1), F.lit(STEPS)), interval, step)

    p, one = F.col("p"), F.lit(1.0)
    flat = F.ln(F.greatest(F.size(p), F.lit(1)).cast("double"))
    a = one
    if entropy_share is not None:
        wanted = flat * entropy_share
        a = F.when(_entropy(p, one) >= wanted, one).otherwise(bisect(lambda m: _entropy(p, m) >= wanted)["lo"])
    row = row.select("all", "p", a.alias("a"))
    if max_repeats is not None:
        # passes over a source: its weight against its share, times the budget against all tokens
        budget = F.least(budget, F.floor(F.coalesce(total.scalar().cast("double"), F.lit(0.0)) * max_repeats))
        most = F.col("all") * max_repeats
        wanted = F.col("all") if budget_tokens is None else F.lit(float(budget_tokens))
        row = row.select("p", "a", (most / F.nullif(F.least(wanted, F.floor(most).cast("double")), F.lit(0.0))).alias("limit"))
        limit = F.col("limit")
        row = row.select("p", F.when(_repeats(p, F.col("a")) <= limit, F.col("a")).otherwise(F.greatest(F.col("a"), bisect(lambda m: _repeats(p, m) > limit)["hi"])).alias("a"))
    row = row.select(F.col("a").alias("exponent"), F.aggregate(p, F.lit(0.0), lambda s, x: s + F.pow(x, F.col("a"))).alias("z"))
    share = F.when(F.col("tokens") > 0, F.col("tokens") / total.scalar().cast("double")).otherwise(0.0)
    out = per.withColumn("share", share).withColumn("exponent", row.select("exponent").scalar())
    out = out.withColumn("weight", F.when(F.col("tokens") > 0, F.pow("share", F.col("exponent")) / row.select("z").scalar()).otherwise(0.0))
    return keep(out.select("source", "n_docs", "tokens", "share", "exponent", "weight", budget.cast("long").alias("budget")), per)


def mix_sources(docs: DataFrame, entropy_share: float | None = ENTROPY_SHARE, max_repeats: float | None = MAX_REPEATS, budget_tokens: int | None = None, seed: int = 17) -> DataFrame:
    """(doc_id, source, n_tokens, weight, passes, copies, block, block_rank): one row per row of ``docs``.

    ``budget_tokens`` (default: all tokens; see ``source_weights`` for one that can't be met) are
    dealt to sources by weight. A document gets one copy for each whole pass over its source and
    one more if it lies before the end of the budget in the permuted order; the document on
    which the budget ends is the last to get it. Documents without words get the copies of the
    whole passes and of their place. Rows without a doc_id are placed by their text. Repeated
    rows are dealt with as rows of their own. Text is read once. ``release`` of the result
    deletes the tables behind it.
    """
    place = lambda k: F.when(F.col("doc_id").isNull(), F.xxhash64(F.lit(k), "text")).otherwise(F.xxhash64(F.lit(k), F.col("doc_id").cast("long")))
    counted = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), token_count(F.col("text")).alias("n_tokens"), place(seed).alias("at"), place(seed + 1).alias("place"))
    counted = materialize(counted, "tokens")
    found = source_weights(counted, entropy_share, max_repeats, budget_tokens)
    weights = materialize(found, "weights")
    release(found)
    plan = weights.withColumn("due", F.col("budget") * F.col("weight")).withColumn("passes", F.when(F.col("tokens") > 0, F.col("due") / F.col("tokens")).otherwise(0.0))
    plan = plan.withColumn("whole", F.floor("passes")).withColumn("rest", F.when(F.col("tokens") > 0, F.round(F.col("due") - F.col("whole") * F.col("tokens"), 3)).otherwise(0.0))
    plan = plan.select(F.col("source").alias("s"), "weight", "passes", "whole", "rest", F.ceil(F.col("n_docs") / BLOCK_DOCS).alias("blocks"))
    dealt = counted.join(plan, F.col("source").eqNullSafe(F.col("s")))
    dealt = dealt.withColumn("block", F.pmod("at", F.col("blocks"))).drop("s", "blocks", "at")
    # Blocks in their permuted order: where each begins and ends in tokens, by ranges of the order, then inside a range.
    sums = dealt.groupBy("source", "block").agg(F.sum("n_tokens").alias("t"))
    sums = sums.withColumn("o", F.xxhash64(F.lit(seed + 2), "source", "block")).withColumn("range", F.shiftright("o", 64 - RANGE_BITS))
    earlier = Window.partitionBy("source").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    ranges = sums.groupBy("source", "range").agg(F.sum("t").alias("t"), F.count("*").alias("n"))
    ranges = ranges.select(F.col("source").alias("s"), F.col("range").alias("g"), *[F.coalesce(F.sum(c).over(earlier), F.lit(0)).alias(f"{c}0") for c in "tn"])
    inside = Window.partitionBy("source", "range").orderBy("o", "block")
    starts = sums.join(ranges, F.col("source").eqNullSafe(F.col("s")) & (F.col("range") == F.col("g")))
    starts = starts.withColumn("end", F.col("t0") + F.sum("t").over(inside)).withColumn("block_rank", (F.col("n0") + F.row_number().over(inside)).cast("int"))
    starts = starts.select(F.col("source").alias("s"), F.col("block").alias("k"), (F.col("end") - F.col("t")).alias("begin"), "end", "block_rank")
    # Only the block in which a source's budget ends is ordered by document.
    placed = dealt.join(starts, F.col("source").eqNullSafe(F.col("s")) & (F.col("block") == F.col("k"))).drop("s", "k")
    ends = (F.col("rest") > F.col("begin")) & (F.col("rest") < F.col("end"))
    before = Window.partitionBy("source", "block").orderBy("place", "doc_id", "n_tokens").rowsBetween(Window.unboundedPreceding, -1)
    cut = placed.filter(ends).withColumn("seen", F.coalesce(F.sum("n_tokens").over(before), F.lit(0)))
    cut = cut.withColumn("extra", (F.col("begin") + F.col("seen") < F.col("rest")).cast("long")).drop("seen")
    plain = placed.filter(~ends).withColumn("extra", ((F.col("rest") > 0) & (F.col("rest") >= F.col("end"))).cast("long"))
    out = plain.unionByName(cut)
    return keep(out.select("doc_id", "source", "n_tokens", "weight", "passes", (F.col("whole") + F.col("extra")).alias("copies"), "block", "block_rank"), counted, weights)
