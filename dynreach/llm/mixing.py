"""Temperature mixing of sources, with DataFrame functions alone.

A source with token share p gets a weight in proportion to p ** exponent. The exponent is found by
repeated section of [0, 1] (each job tries SECTIONS exponents at once over the sources' totals, and
the bracket around the target shrinks) so that the weights' entropy reaches a target, or no
source repeats more often than a limit. The normalised weights become token budgets: each source
is drawn in whole blocks of all its documents, and the last block is the part of a seeded
permutation that fits what is left of the budget. `draw` says how many blocks hold a row, `permuted` gives each copy its
block and its place in that block's permutation, and `mixed` writes the copies in that order.

The part of the last block, and places, are found by running sums in two levels: a source's hash range is
cut into buckets of about BUCKET_ROWS documents, their sums give each bucket its start, and
windows run inside buckets only, so no source is gathered in one task. Documents are not shuffled for that; only `mixed`
shuffles them, once, into their order.

Tokens are bytes / BYTES_PER_TOKEN, one at least, unless a column of counts is named. Defined cases: a null source is a
source of its own; null texts count as one token; equal rows are drawn alike by the last block and have places of their own;
with an empty table there are no rows; extra columns pass through, but for those named as the columns that `draw` and
`permuted` add, which these replace.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dynreach.llm.common import cut

BYTES_PER_TOKEN, BUCKET_ROWS, SECTIONS, ROUNDS = 4, 1_000, 32, 5
#: Tables of sources up to this many rows are broadcast; larger ones are joined by shuffle.
MOST_BROADCAST = 100_000
#: Tokens of the rows that `mixed` sorts together.
CHUNK_TOKENS = 4_000_000
DRAWN = ("mix_tokens", "mix_exponent", "mix_weight", "mix_blocks", "mix_last", "mix_copies")


def tokens(text_col: str = "text") -> Column:
    return F.greatest(F.ceil(F.coalesce(F.octet_length(text_col), F.lit(0)) / BYTES_PER_TOKEN), F.lit(1)).cast("long")


def source_totals(rows: DataFrame) -> DataFrame:
    """(source, total, docs, everything, p) from rows with __source and __tokens."""
    per = rows.groupBy("__source").agg(F.sum("__tokens").alias("total"), F.count("*").alias("docs"))
    everything = per.agg(F.sum("total").alias("everything"))
    return per.join(F.broadcast(everything)).withColumn("p", F.col("total") / F.col("everything"))  # one row


def measures(totals: DataFrame, exponents: list[float]) -> list[tuple[float, float, float, float]]:
    """(exponent, entropy over its maximum, largest and smallest repetition of the total) for each exponent."""
    e = F.col("e")
    power = F.pow("p", e)
    tried = totals.select("p", F.explode(F.array(*map(F.lit, exponents))).alias("e")).groupBy("e").agg(
        F.sum(power).alias("z"), F.sum(power * F.log("p")).alias("zl"), F.max(F.pow("p", e - 1)).alias("most"), F.min(F.pow("p", e - 1)).alias("least"), F.count("*").alias("n")
    )
    entropy = F.when(F.col("n") > 1, (F.log("z") - e * F.col("zl") / F.col("z")) / F.log("n")).otherwise(F.lit(1.0))
    return [tuple(r) for r in tried.select("e", entropy, F.col("most") / F.col("z"), F.col("least") / F.col("z")).orderBy("e").collect()]


def find_exponent(totals: DataFrame, target_entropy: float | None = None, repeat_limit: float | None = None, cover: bool = False) -> float:
    """The smallest exponent in [0, 1] that keeps to the repetition limit, or the largest whose
    entropy (a share of the largest possible) is at least the target; given both, the limit rules.

    cover: repetitions are counted in blocks of the source drawn least, which is drawn once.
    """
    if repeat_limit is None and target_entropy is None:
        return 1.0

    def low_enough(m: tuple) -> bool:
        """True from some exponent on."""
        if repeat_limit is not None:
            return (m[2] / m[3] if cover else m[2]) <= repeat_limit * (1 + 1e-12)
        return m[1] < target_entropy

    low, high = 0.0, 1.0
    for k in range(ROUNDS):
        grid = [low + (high - low) * i / SECTIONS for i in range(SECTIONS + 1)]
        found = measures(totals, grid)
        if not found:
            return 1.0
        met = [m[0] for m in found if low_enough(m)]
        if k == 0 and met and met[0] == 0.0:
            return 0.0
        if not met:
            return 1.0
        missed = [m[0] for m in found if m[0] < met[0]]
        low, high = missed[-1], met[0]
    return high if repeat_limit is not None else low


def plan(rows: DataFrame, target_entropy: float | None, repeat_limit: float | None, budget: int | None, cover: bool) -> DataFrame:
    """(source, total, docs, exponent, weight, budget, blocks, rest, buckets): rest is what the last block may hold."""
    totals = cut(source_totals(rows))
    exponent = find_exponent(totals, target_entropy, repeat_limit, cover)
    powered = totals.withColumns({"exponent": F.lit(exponent), "power": F.pow("p", F.lit(exponent))})
    sums = powered.agg(F.sum("power").alias("z"), F.max(F.col("total") / F.col("power")).alias("cover"))
    weighted = powered.join(F.broadcast(sums)).withColumn("weight", F.col("power") / F.col("z"))  # one row
    if cover:
        share = F.col("power") * F.col("cover")
    else:
        share = F.col("weight") * (F.col("everything") if budget is None else F.lit(budget))
    weighted = weighted.withColumn("budget", F.floor(share + 1e-6).cast("long")).withColumn("blocks", F.floor(F.col("budget") / F.col("total")).cast("int"))
    rest = F.col("budget") - F.col("blocks") * F.col("total")
    return weighted.select("__source", "total", "docs", "exponent", "weight", "budget", "blocks", rest.alias("rest"), F.ceil(F.col("docs") / BUCKET_ROWS).cast("long").alias("buckets"))


def _drawn(docs: DataFrame, target_entropy: float | None, repeat_limit: float | None, budget: int | None, cover: bool, seed: int, id_col: str, source_col: str, token_count: Column | None) -> DataFrame:
    """The input's rows whole as __row, so that no name clashes, with what is drawn of them; nothing whole is shuffled."""
    rows = docs.select(
        F.struct(*[F.col(c) for c in docs.columns]).alias("__row"),
        F.struct(F.col(source_col)).alias("__source"),
        F.col(id_col).alias("__id"),
        (token_count if token_count is not None else tokens()).alias("__tokens"),
    ).withColumn("__hash", F.shiftrightunsigned(F.xxhash64(F.lit(seed), "__id", "__source", "__tokens"), 11))
    planned = cut(plan(rows, target_entropy, repeat_limit, budget, cover))
    side = planned.select("__source", F.col("weight").alias("mix_weight"), F.col("exponent").alias("mix_exponent"), F.col("blocks").alias("mix_blocks"), "rest", "buckets", "docs", "total")
    few = planned.count() <= MOST_BROADCAST
    small = F.broadcast if few else (lambda df: df)
    placed = rows.join(small(side), "__source").withColumn("__bucket", F.floor(F.col("__hash") / float(1 << 53) * F.col("buckets")))
    limits = cut(_limits(placed, small))
    last = (F.col("__bucket") < F.col("cut_bucket")) | ((F.col("__bucket") == F.col("cut_bucket")) & (F.col("__hash") <= F.col("cut_hash")))
    return placed.join(small(limits), "__source", "left").withColumn("mix_last", F.coalesce(last, F.lit(False))).withColumn("mix_copies", F.col("mix_blocks") + F.col("mix_last").cast("int"))


def _limits(placed: DataFrame, small) -> DataFrame:
    """(source, cut_bucket, cut_hash): the last place of the seeded order up to which rows fit the rest of the budget."""
    sums = placed.groupBy("__source", "__bucket", "rest").agg(F.sum("__tokens").alias("in_bucket"))
    ahead = Window.partitionBy("__source").orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.withColumn("start", F.coalesce(F.sum("in_bucket").over(ahead), F.lit(0)))
    ends = cut(starts.where("start <= rest and rest < start + in_bucket").select("__source", F.col("__bucket").alias("cut_bucket"), "start"))
    here = placed.join(small(ends), "__source").where(F.col("__bucket") == F.col("cut_bucket"))
    equal = here.groupBy("__source", "cut_bucket", "start", "rest", "__hash").agg(F.sum("__tokens").alias("n"))  # equal rows fall together
    upto = F.col("start") + F.sum("n").over(Window.partitionBy("__source").orderBy("__hash").rowsBetween(Window.unboundedPreceding, 0))
    fits = F.max(F.when(F.col("upto") <= F.col("rest"), F.col("__hash")))
    return equal.withColumn("upto", upto).groupBy("__source", "cut_bucket").agg(F.coalesce(fits, F.lit(-1)).alias("cut_hash"))


def _own(docs: DataFrame, added: tuple[str, ...]) -> list[Column]:
    return [F.col("__row").getField(c).alias(c) for c in docs.columns if c not in added]


def draw(
    docs: DataFrame,
    target_entropy: float | None = None,
    repeat_limit: float | None = 2.0,
    budget: int | None = None,
    cover: bool = False,
    seed: int = 13,
    id_col: str = "doc_id",
    source_col: str = "source",
    token_count: Column | None = None,
) -> DataFrame:
    """The input's rows with mix_tokens, mix_exponent, mix_weight, mix_blocks, mix_last, mix_copies; input columns of these names are replaced."""
    drawn = _drawn(docs, target_entropy, repeat_limit, budget, cover, seed, id_col, source_col, token_count)
    return drawn.select(*_own(docs, DRAWN), F.col("__tokens").alias(DRAWN[0]), *DRAWN[1:])


def _blocks(drawn: DataFrame) -> DataFrame:
    """One row for each block that draws a row; one with a null block for rows that none draws."""
    return drawn.withColumn("mix_block", F.explode_outer(F.when(F.col("mix_copies") > 0, F.sequence(F.lit(0), F.col("mix_copies") - 1))))


def permuted(
    docs: DataFrame,
    target_entropy: float | None = None,
    repeat_limit: float | None = 2.0,
    budget: int | None = None,
    cover: bool = False,
    seed: int = 13,
    id_col: str = "doc_id",
    source_col: str = "source",
    token_count: Column | None = None,
) -> DataFrame:
    """One row for each copy drawn, as `draw` gives them, with mix_block (from 0; a row that the last, partial block takes has
    as its last block the number of whole ones) and mix_place, its place from 0 in that block's own seeded permutation of
    the source. Rows that are not drawn have one row with both null.
    """
    drawn = _drawn(docs, target_entropy, repeat_limit, budget, cover, seed, id_col, source_col, token_count)
    # the row's number parts equal rows, so that they get places of their own and never share a bucket by force
    turn = F.shiftrightunsigned(F.xxhash64(F.lit(seed), "mix_block", "__id", "__source", "__number"), 11)
    rows = cut(_blocks(drawn.withColumn("__number", F.monotonically_increasing_id())))  # written, as it is read twice and numbers must stay
    rows = rows.withColumn("__turn", turn)
    rows = rows.withColumn("__part", F.floor(F.col("__turn") / float(1 << 53) * F.col("buckets")))
    key = ["__source", "mix_block", "__part"]
    sizes = rows.where("mix_block is not null").groupBy(*key).agg(F.count("*").alias("n"))
    ahead = Window.partitionBy("__source", "mix_block").orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select(*key, F.coalesce(F.sum("n").over(ahead), F.lit(0)).alias("start"))
    row = F.row_number().over(Window.partitionBy(*key).orderBy("__turn", "__number"))
    undrawn = rows.where("mix_block is null").withColumn("mix_place", F.lit(None).cast("long"))
    places = rows.where("mix_block is not null").join(starts, key).withColumn("mix_place", (F.col("start") + row - 1).cast("long"))
    names = DRAWN[1:] + ("mix_block", "mix_place")
    out = [*_own(docs, (*DRAWN, "mix_block", "mix_place")), F.col("__tokens").alias(DRAWN[0]), *names]
    return places.select(*out).unionByName(undrawn.select(*out))


def mixed(docs: DataFrame, repeat_limit: float = 2.0, seed: int = 13, chunk_tokens: int = CHUNK_TOKENS, id_col: str = "doc_id", source_col: str = "source", token_count: Column | None = None) -> DataFrame:
    """Documents as often as they are drawn, with their own columns. Each source is drawn once at least (`cover`), so
    none is lost. Rows come in chunks of about chunk_tokens: a source's blocks follow one another, each in its
    own seeded permutation, and all sources advance in step, so that each chunk holds them by their weights.
    """
    drawn = _blocks(_drawn(docs, None, repeat_limit, None, True, seed, id_col, source_col, token_count))
    turn = F.shiftrightunsigned(F.xxhash64(F.lit(seed), "mix_block", "__id", "__source", "__tokens"), 11) / float(1 << 53)
    whole = F.col("mix_blocks") + F.col("rest") / F.col("total")
    share = F.when(F.col("mix_block") < F.col("mix_blocks"), F.lit(1.0)).otherwise(F.col("rest") / F.col("total"))  # what the block is of a whole one
    at = drawn.withColumn("__at", (F.col("mix_block") + turn * share) / whole)
    tokens_drawn = docs.select((token_count if token_count is not None else tokens()).alias("n")).agg(F.sum("n")).first()[0] or 0
    chunks = max(1, -(-tokens_drawn // chunk_tokens))
    at = at.withColumn("__chunk", F.floor(F.col("__at") * chunks))
    return at.repartition(chunks, "__chunk").sortWithinPartitions("__chunk", "__at").select(*[F.col("__row").getField(c).alias(c) for c in docs.columns])
