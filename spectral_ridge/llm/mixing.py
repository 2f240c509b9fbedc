"""Temperature mixing of sources, in DataFrame operations only.

Source token shares are raised to an exponent in [0, 1]; bisection finds the exponent that meets
a target entropy or a repetition limit; the normalised weights then become whole and partial
passes over each source. A source's documents are dealt into blocks of about equal tokens; each
pass visits the blocks in an order of its own, and the last, partial pass stops where the
source's token budget ends, inside a block if need be.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise

WORD = r"[^\x20\x09-\x0D]+"


@dataclass(frozen=True)
class MixPlan:
    """Targets of a mixture.

    ``repetition_limit``: no source is passed over more often than this, counting the largest
    source as one pass. ``entropy``: target as a part of the largest possible entropy (used where
    ``repetition_limit`` is None). ``budget_tokens``: tokens to emit; None means the smallest
    budget that emits every document at least once. ``block_tokens``: tokens in a block.
    """

    repetition_limit: float | None = 2.0
    entropy: float | None = None
    budget_tokens: int | None = None
    block_tokens: int = 65_536
    seed: int = 7
    steps: int = 40
    steps_at_once: int = 4


def _hex_number(text: Column) -> Column:
    """The first 60 bits of an MD5 as a number."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def _identity(docs: DataFrame) -> list[Column]:
    """What tells rows apart beside id and source: bytes of the text, and its MD5 where the id is null."""
    text = F.coalesce(docs["text"], F.lit(""))
    unnamed = F.when(docs["doc_id"].isNull(), F.md5(text.cast("binary")))
    return [F.octet_length(text).alias("text_bytes"), unnamed.alias("unnamed")]


def token_table(docs: DataFrame) -> DataFrame:
    """(doc_id, source, n_tokens, text_bytes, unnamed): words of the whole text; null text has none."""
    words = F.regexp_count(F.coalesce(docs["text"], F.lit("")), F.lit(WORD)).cast("long")
    return docs.select(docs["doc_id"], docs["source"], words.alias("n_tokens"), *_identity(docs))


def bisect_exponent(totals: DataFrame, plan: MixPlan) -> float:
    """The exponent, by halving [0, 1] ``plan.steps`` times. ``totals``: (source, tokens > 0).

    Each distributed pass over the sources evaluates the midpoints of several halvings at once,
    so the result equals that of one halving after another. The driver sees only one row a pass.
    """
    top, low, count, whole = totals.agg(F.max("tokens"), F.min("tokens"), F.count("*"), F.sum("tokens")).first()
    if not count:
        return 1.0
    done, lower, upper = 0, 0.0, 1.0
    while done < plan.steps:
        depth = min(plan.steps_at_once, plan.steps - done)
        grid = [lower + (upper - lower) * k / 2**depth for k in range(1, 2**depth)]
        if plan.repetition_limit is not None:
            meets = [F.max(F.pow(F.lit(float(top)) / F.col("tokens"), F.lit(1.0 - a))) <= plan.repetition_limit for a in grid]
        else:
            share = F.col("tokens") / F.lit(float(whole))
            powers = [F.pow(share, F.lit(a)) for a in grid]
            target = plan.entropy * F.log(F.lit(float(count)))
            meets = [F.log(F.sum(p)) - F.sum(p * F.log(p)) / F.sum(p) <= target for p in powers]
        ok = totals.agg(F.array(*meets)).first()[0]  # False below the exponent sought, True from it on
        for _ in range(depth):
            middle = (lower + upper) / 2
            if ok[grid.index(middle)]:
                upper = middle
            else:
                lower = middle
        done += depth
    return upper


def mix_weights(tokens: DataFrame, plan: MixPlan = MixPlan()) -> DataFrame:
    """(source, tokens, weight, epochs, n_blocks) of each source, null source included. Sources
    without any token get weight 0 and one pass."""
    totals = materialise(tokens.groupBy("source").agg(F.sum("n_tokens").alias("tokens")), "mix-totals")
    filled = totals.where("tokens > 0")
    alpha = bisect_exponent(filled, plan)
    count, whole, top = filled.agg(F.count("*"), F.sum("tokens"), F.max("tokens")).first()
    if not count:
        return totals.select("source", "tokens", F.lit(0.0).alias("weight"), F.lit(1.0).alias("epochs"), F.lit(1).cast("long").alias("n_blocks"))
    power = F.when(F.col("tokens") > 0, F.pow(F.col("tokens") / F.lit(float(whole)), F.lit(alpha))).otherwise(0.0)
    norm = filled.agg(F.sum(F.pow(F.col("tokens") / F.lit(float(whole)), F.lit(alpha)))).first()[0]
    if plan.budget_tokens is None:
        epochs = F.pow(F.lit(float(top)) / F.col("tokens"), F.lit(1.0 - alpha))
    else:
        epochs = F.lit(float(plan.budget_tokens)) * power / F.lit(norm) / F.col("tokens")
    return totals.select(
        "source", "tokens", (power / F.lit(norm)).alias("weight"), F.when(F.col("tokens") > 0, epochs).otherwise(1.0).alias("epochs"), F.greatest(F.lit(1).cast("long"), F.ceil(F.col("tokens") / F.lit(plan.block_tokens))).alias("n_blocks"),
    )


def _block_places(sums: DataFrame, plan: MixPlan, bins: int = 4096) -> DataFrame:
    """(block_of, block_epoch, block_id, block_rank, tokens_before): the order of a pass over each
    source's blocks, by hash.

    ``sums``: (of, epoch, block, block_tokens). Blocks are ordered inside ranges of the hash, and the
    ranges, at most ``bins`` of a pass, after each other: no source's blocks meet in one task.
    """
    name = F.coalesce(F.col("of"), F.lit("-"))
    salted = F.concat_ws(":", F.lit("order"), F.lit(plan.seed), name, F.col("epoch").cast("string"), F.col("block").cast("string"))
    keyed = sums.withColumn("key", F.md5(salted.cast("binary")))
    keyed = keyed.withColumn("bin", F.floor(F.conv(F.substring("key", 1, 4), 16, 10).cast("int") * F.lit(bins) / F.lit(65_536)))
    ranges = keyed.groupBy("of", "epoch", "bin").agg(F.count("*").alias("k"), F.sum("block_tokens").alias("t"))
    passed = Window.partitionBy("of", "epoch").orderBy("bin").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ranges = ranges.select(
        F.col("of").alias("range_of"),
        F.col("epoch").alias("range_epoch"),
        F.col("bin").alias("range_bin"),
        (F.sum("k").over(passed) - F.col("k")).alias("blocks_before"),
        (F.sum("t").over(passed) - F.col("t")).alias("range_before"),
    )
    here = Window.partitionBy("of", "epoch", "bin").orderBy("key", "block")
    upto = here.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    inside = keyed.withColumns({"rank": F.row_number().over(here) - 1, "ahead": F.sum("block_tokens").over(upto) - F.col("block_tokens")})
    same = F.col("of").eqNullSafe(F.col("range_of")) & (F.col("epoch") == F.col("range_epoch")) & (F.col("bin") == F.col("range_bin"))
    return inside.join(ranges, same).select(
        F.col("of").alias("block_of"),
        F.col("epoch").alias("block_epoch"),
        F.col("block").alias("block_id"),
        (F.col("blocks_before") + F.col("rank")).alias("block_rank"),
        (F.col("range_before") + F.col("ahead")).alias("tokens_before"),
    )


def _emitted(docs: DataFrame, plan: MixPlan) -> DataFrame:
    """Rows of the mixture with what tells them apart."""
    counted = token_table(docs).withColumn("row", F.monotonically_increasing_id())
    tokens = materialise(counted, "mix-tokens")
    weights = materialise(mix_weights(tokens, plan), "mix-weights")
    size_ok = weights.count() <= 100_000  # under about 10 MB; beyond it, a shuffled join
    named = weights.select(F.col("source").alias("of"), F.col("tokens").alias("source_tokens"), "epochs", "n_blocks")
    side = F.broadcast(named) if size_ok else named
    # rows without an id are dealt by their place in the written table, not all into one block
    ids = F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("-"), F.col("row").cast("string")))
    code = _hex_number(F.concat_ws(":", F.lit("block"), F.lit(plan.seed), ids))
    dealt = tokens.join(side, F.col("source").eqNullSafe(F.col("of"))).withColumn("block", F.pmod(code, F.col("n_blocks")))
    epoch = F.explode(F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil(F.col("epochs")).cast("int") - 1)))
    passes = dealt.withColumn("epoch", epoch).where("epochs > 0")
    sums = dealt.groupBy("of", "epochs", "block").agg(F.sum("n_tokens").alias("block_tokens")).withColumn("epoch", epoch)
    blocks = _block_places(sums.drop("epochs"), plan)
    here = Window.partitionBy("source", "epoch", "block").orderBy("key", "doc_id", "n_tokens")
    upto = here.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    inside = passes.withColumn("key", F.md5(F.concat_ws(":", F.lit("row"), F.lit(plan.seed), ids, F.col("epoch").cast("string")).cast("binary")))
    inside = inside.withColumns({"slot": F.row_number().over(here) - 1, "ahead": F.sum("n_tokens").over(upto) - F.col("n_tokens")})
    same = F.col("source").eqNullSafe(F.col("block_of")) & (F.col("epoch") == F.col("block_epoch")) & (F.col("block") == F.col("block_id"))
    joined = inside.join(blocks, same).withColumn("begin", F.col("tokens_before") + F.col("ahead"))
    # a document at the end of a whole pass keeps its place even if it has no words
    place = F.col("epoch") + F.when(F.col("source_tokens") > 0, F.col("begin") / F.col("source_tokens")).otherwise(0.0)
    position = F.round(F.least(F.lit(1.0), place / F.col("epochs")), 9)
    return joined.where((F.col("epoch") + 1 <= F.col("epochs")) | (place < F.col("epochs"))).withColumn("position", position)


def mix_documents(docs: DataFrame, plan: MixPlan = MixPlan()) -> DataFrame:
    """Rows of the mixture: (doc_id, source, n_tokens, epoch, block, block_rank, slot, position).

    ``epoch`` counts passes from 0, ``block_rank`` is the block's place in that pass, ``slot`` the
    document's place in its block, ``position`` in [0, 1] its place in the whole mixture: sorted
    by it, every prefix holds the sources at their target weights. A partial pass stops at the
    first document that begins at or past the source's budget. Null sources form one source of
    their own; documents without words are emitted with the pass they fall in; repeated rows are
    emitted each, in one block; an empty table gives an empty result; other columns are ignored.
    """
    longs = [F.col(c).cast("long").alias(c) for c in ("block_rank", "slot")]
    return _emitted(docs, plan).select("doc_id", "source", "n_tokens", "epoch", "block", *longs, "position")


def mixed_documents(docs: DataFrame, plan: MixPlan = MixPlan()) -> DataFrame:
    """The documents themselves, each as often as the mixture emits it, with their own columns.

    Only how often each pass emits it is joined to a text. Rows that share id, source and bytes of
    text are copies: where a partial pass emits k of them, these are the first k.
    """
    keys = ["doc_id", "source", "text_bytes", "unnamed"]
    per_pass = _emitted(docs, plan).groupBy(*keys, "epoch").agg(F.count("*").cast("int").alias("mix_k"))
    often = per_pass.groupBy(*keys).agg(F.collect_list("mix_k").alias("mix_ks"), F.max("mix_k").alias("mix_copies"))
    often = materialise(often.toDF(*[f"mix_{k}" for k in keys], "mix_ks", "mix_copies"), "mix-times")
    size, unnamed = _identity(docs)
    told = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("mix_row"), docs["doc_id"], docs["source"], size, unnamed)
    same = reduce(lambda a, b: a & b, [F.col(k).eqNullSafe(F.col(f"mix_{k}")) for k in keys])
    rows = told.join(often.where("mix_copies = 1"), same).withColumn("mix_copy", F.lit(1))
    repeated = often.where("mix_copies > 1")
    if not repeated.isEmpty():  # only these rows need a number among their copies
        copy = F.row_number().over(Window.partitionBy(*keys).orderBy("mix_copies"))
        rows = rows.unionByName(told.join(repeated, same).withColumn("mix_copy", copy))
    passes = F.size(F.filter("mix_ks", lambda k: k >= F.col("mix_copy")))
    return rows.withColumn("mix_pass", F.explode(F.sequence(F.lit(1), passes))).select("mix_row.*")
