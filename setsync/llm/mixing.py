"""Mixing sources to target weights by highest quotients, with DataFrame operations alone.

Sources get token targets by weight, none above ``cap`` times its own size (the excess goes round
again by weight). Sainte-Lague apportionment turns targets into whole blocks of equal size per
source, then a source's blocks into whole quotas per shard, each by the highest quotients
share / (2k + 1). A shard reads its documents in seeded order as one run of words, cut into blocks;
it takes whole passes first and then blocks in seeded order. The words between a quota and its
target move to shards with room, so a source meets its target to the word.

Defined cases: null texts and texts of white space have size 0 and take 0; the null source comes
last; ids that repeat or are null are dealt by their texts too; ties in the seeded order fall to the id, the size, the text's hash, then any order of equal rows; repeated rows
are documents of their own; empty tables give no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from setsync.llm.shared import cut, table

WEIGHTS = (3, 1, 2)
SHARE_PERCENT = 150
CAP = 2
BLOCK = 1024
SHARD_ROWS = 4096
SEED = "mix-1"
STRIDES = 16
WORD = r"[^\x20\x09-\x0D]+"
SPACE = r"[\x20\x09-\x0D]"


def primes_from(start: int, count: int) -> list[int]:
    """The first ``count`` odd primes above ``start``."""
    found, x = [], start | 1
    while len(found) < count:
        x += 2
        if all(x % d for d in range(3, int(x**0.5) + 1, 2)):
            found.append(x)
    return found


#: Primes above any number of blocks in a shard: the multiples of each run through all of them.
STRIDE = primes_from(1 << 31, STRIDES)


def seeded(*parts: Column) -> Column:
    """A number below 2^60 from the seed and ``parts``."""
    text = F.concat_ws(":", F.lit(SEED), *[F.coalesce(p.cast("string"), F.lit("-")) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = WEIGHTS, percent: int = SHARE_PERCENT, cap: int = CAP) -> DataFrame:
    """``source, source_size, n_docs, target, words``: one row a source. Needs ``source, size``.

    In falling order of weight per word, source i is held at ``cap * size`` exactly if that is below
    its share of what the sources before it leave.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_docs"))
    named = W.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(named) - 1, F.lit(len(weights))) + 1).cast("int"))
    order = W.orderBy(F.col("most") / F.col("weight"), F.col("source").asc_nulls_last())
    before = order.rowsBetween(W.unboundedPreceding, -1)
    onward = order.rowsBetween(W.currentRow, W.unboundedFollowing)
    everything = W.partitionBy(F.lit(1))
    held = (
        per.withColumn("weight", weight.cast("long"))
        .withColumn("most", F.col("source_size") * cap)
        .withColumn("pool", F.sum("source_size").over(everything) * F.lit(percent / 100))
        .withColumn("rest", F.col("pool") - F.coalesce(F.sum("most").over(before), F.lit(0)))
        .withColumn("weights_left", F.sum("weight").over(onward))
        .withColumn("held", F.col("most") * F.col("weights_left") <= F.col("rest") * F.col("weight"))
    )
    free = W.partitionBy(F.lit(1))
    shared = (
        held.withColumn("free_rest", F.first("pool").over(free) - F.sum(F.when(F.col("held"), F.col("most")).otherwise(0)).over(free))
        .withColumn("free_weight", F.sum(F.when(F.col("held"), 0).otherwise(F.col("weight"))).over(free))
    )
    target = F.when(F.col("held"), F.col("most").cast("double")).otherwise((F.col("weight") * F.col("free_rest")).cast("double") / F.col("free_weight"))
    return shared.select("source", "source_size", "n_docs", target.alias("target"), F.round(target).cast("long").alias("words"))


def highest_quotients(parties: DataFrame, group: list[str], share: str, seats: str, tie: list[Column]) -> DataFrame:
    """Adds ``quota``: the ``seats`` of a group given out by the highest quotients share / (2k + 1).

    Rounding ``seats * share / total`` is Sainte-Lague's answer but for a few seats. Each party
    therefore enters with the quotients around its rounded number only, as many as the gap can move.
    """
    g = W.partitionBy(*group) if group else W.partitionBy(F.lit(1))
    near = parties.withColumn("_total", F.sum(share).over(g)).withColumn(
        "_near", F.when(F.col("_total") > 0, F.floor(F.col(seats) * F.col(share) / F.col("_total") + 0.5)).otherwise(0).cast("long")
    )
    near = near.withColumn("_gap", F.abs(F.col(seats) - F.sum("_near").over(g)))
    reach = F.when(F.col("_total") > 0, F.ceil(F.col("_gap") * F.col(share) / F.col("_total"))).otherwise(0) + 1
    near = near.withColumn("_floor", F.greatest(F.lit(0), F.col("_near") - reach).cast("long"))
    near = near.withColumn("_open", F.col(seats) - F.sum("_floor").over(g))
    tries = near.withColumn("_k", F.explode(F.sequence(F.col("_floor"), F.col("_near") + reach)))
    ranked = tries.withColumn("_rank", F.row_number().over((W.partitionBy(*group) if group else W.partitionBy(F.lit(1))).orderBy(F.desc(F.col(share) / (2 * F.col("_k") + 1)), *tie)))
    won = F.sum(F.when((F.col("_rank") <= F.col("_open")) & (F.col(share) > 0), 1).otherwise(0))
    keep = [c for c in parties.columns]
    return ranked.groupBy(*keep).agg((F.first("_floor") + won).cast("long").alias("quota"))


def shard_words(sizes: DataFrame, targets: DataFrame, block: int = BLOCK, cap: int = CAP) -> DataFrame:
    """``source, shard, shard_size, take``: words to take from each shard. Needs ``source, shard, size``."""
    per_source = targets.withColumn("_seats", F.round(F.sum("words").over(W.partitionBy(F.lit(1))) / block).cast("long"))
    blocks = highest_quotients(per_source, [], "words", "_seats", [F.col("source").asc_nulls_last()])
    shards = sizes.groupBy("source", "shard").agg(F.sum("size").alias("shard_size"))
    known = blocks.select(F.col("source").alias("_source"), "words", F.col("quota").alias("_blocks"))
    shards = shards.join(known, F.col("source").eqNullSafe(F.col("_source"))).drop("_source")
    quotas = highest_quotients(shards, ["source"], "shard_size", "_blocks", [F.col("shard")])
    g = W.partitionBy("source")
    run = g.orderBy("shard").rowsBetween(W.unboundedPreceding, -1)
    first = quotas.withColumn("_take", F.least(F.col("quota") * block, F.col("shard_size") * cap))
    first = first.withColumn("_more", F.col("words") - F.sum("_take").over(g))
    room = F.when(F.col("_more") >= 0, F.col("shard_size") * cap - F.col("_take")).otherwise(F.col("_take"))
    first = first.withColumn("_room", room).withColumn("_before", F.coalesce(F.sum("_room").over(run), F.lit(0)))
    step = F.greatest(F.lit(0), F.least(F.col("_room"), F.abs("_more") - F.col("_before")))
    return first.select("source", "shard", "shard_size", (F.col("_take") + F.signum("_more").cast("long") * step).alias("take"))


def mix(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source",
    block: int = BLOCK, shard_rows: int = SHARD_ROWS, carry: bool = False,
) -> DataFrame:
    """``doc_id, source, size, source_size, target, taken, passes, parts``: what the mix takes of each row.

    ``taken`` is ``passes`` times the size plus the words of ``parts`` (first word and number of words
    in the row); blocks that begin or end inside a document take a part of it. ``carry`` adds the row
    of ``docs`` as the struct ``_row``.
    """
    # Sizes are needed three times and are narrow; texts are read once.
    wide = docs.select(
        F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"),
        F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long").alias("size"),
        F.md5(F.coalesce(F.col(text_col), F.lit(""))).alias("_tie"), *([F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")] if carry else []),
    )
    rows = cut(wide.drop("_row"))
    targets = cut(source_targets(rows))
    few = targets.select(F.col("source").alias("_source"), "source_size", "target", F.ceil(F.col("n_docs") / shard_rows).cast("long").alias("_shards"))

    def dealt(frame: DataFrame) -> DataFrame:
        known = frame.join(few, F.col("source").eqNullSafe(F.col("_source"))).drop("_source").withColumn("_key", seeded(F.col("doc_id"), F.col("_tie")))
        return known.withColumn("shard", F.pmod("_key", F.col("_shards")))

    quotas = shard_words(dealt(rows), targets, block).select(F.col("source").alias("_source"), F.col("shard").alias("_shard"), "shard_size", "take")
    order = W.partitionBy("source", "shard").orderBy("_key", "doc_id", "size", "_tie").rowsBetween(W.unboundedPreceding, W.currentRow)
    run = dealt(wide if carry else rows).withColumn("_to", F.sum("size").over(order)).withColumn("_from", F.col("_to") - F.col("size"))
    run = run.join(quotas, F.col("source").eqNullSafe(F.col("_source")) & (F.col("shard") == F.col("_shard")))
    whole = F.floor(F.col("shard_size") / block)
    passes = F.when(F.col("shard_size") > 0, F.floor(F.col("take") / F.col("shard_size"))).otherwise(0)
    run = (
        run.withColumn("_n", whole.cast("long"))
        .withColumn("_passes", passes.cast("long"))
        .withColumn("_rest", (F.col("take") - F.col("_passes") * F.col("shard_size")).cast("long"))
        .withColumn("_turn", F.pmod(seeded(F.col("source"), F.col("shard"), F.lit("turn")), F.greatest(F.col("_n"), F.lit(1))))
        .withColumn("_stride", F.element_at(F.array(*map(F.lit, STRIDE)), (F.pmod(seeded(F.col("source"), F.col("shard"), F.lit("stride")), F.lit(STRIDES)) + 1).cast("int")))
    )

    def place(k: Column) -> Column:
        """The seeded rank of block k; the short last block comes last."""
        turned = F.pmod(k * F.pmod(F.col("_stride"), F.greatest(F.col("_n"), F.lit(1))) + F.col("_turn"), F.greatest(F.col("_n"), F.lit(1)))
        return F.when(k < F.col("_n"), turned).otherwise(F.col("_n"))

    def words(k: Column) -> Column:
        """Of the row's words in block k, those that its rank leaves in."""
        upto = k * block + F.greatest(F.lit(0), F.least(F.lit(block), F.col("_rest") - place(k) * block))
        return F.greatest(F.lit(0), F.least(F.col("_to"), upto) - F.greatest(F.col("_from"), k * block))

    blocks = F.sequence(F.floor(F.col("_from") / block).cast("long"), F.floor((F.col("_to") - 1) / block).cast("long"))
    parts = F.transform(blocks, lambda k: F.struct((F.greatest(F.col("_from"), k * block) - F.col("_from")).alias("at"), words(k).cast("long").alias("n")))
    parts = F.when(F.col("size") > 0, F.filter(parts, lambda p: p["n"] > 0))
    return run.withColumn("parts", parts).select(
        "doc_id", "source", "size", "source_size", "target",
        (F.col("_passes") * F.col("size") + F.coalesce(F.aggregate("parts", F.lit(0).cast("long"), lambda s, p: s + p["n"]), F.lit(0))).cast("long").alias("taken"),
        F.when(F.col("size") > 0, F.col("_passes")).otherwise(0).alias("passes"), "parts", *(["_row"] if carry else []),
    )


def mixed_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The mix as rows with the columns of ``docs``: a copy for each pass and one for each part that a block takes.

    A part keeps its words and the white space after each. ``n_chars``, if there, follows the text.
    """
    taken = mix(docs, id_col, text_col, source_col, carry=True).where("taken > 0")
    text = F.col(f"_row.{text_col}")
    spelled = F.regexp_extract_all(text, F.lit(f"({WORD}{SPACE}*)"), F.lit(1))
    size = F.greatest(F.col("size"), F.lit(1))  # rows that take words have some, but may be tested in any order
    cutting = F.col("taken") % size != 0
    words = F.when(cutting, spelled)
    parts = F.transform("parts", lambda p: F.array_join(F.slice(F.col("_spelled"), (p["at"] + 1).cast("int"), p["n"].cast("int")), ""))
    copies = F.array_repeat(text, F.floor(F.col("taken") / size).cast("int"))
    whole = taken.withColumn("_spelled", words).withColumn("_texts", F.when(cutting, F.concat(copies, parts)).otherwise(copies))
    rows = whole.select("_row", F.explode("_texts").alias("_text"))
    new = {text_col: F.col("_text"), "n_chars": F.length("_text").cast("long")}
    return rows.select(*[new.get(c, F.col(f"_row.`{c}`")).alias(c) for c in docs.columns])


def op6_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op6_sql(block: int = BLOCK, shard_rows: int = SHARD_ROWS) -> str:
    """The same mix in DuckDB, for unique ids: quotients are listed seat by seat instead of around a rounding."""
    key = lambda text: f"(('0x' || substr(md5('{SEED}:' || {text}), 1, 15))::BIGINT)"
    weights = f"list_value({', '.join(map(str, WEIGHTS))})"
    return f"""with rows as (select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{WORD}'))::BIGINT size, {key("coalesce(doc_id::varchar, '-') || ':' || md5(coalesce(text, ''))")} k from documents),
    per as (select source, sum(size)::BIGINT source_size, count(*) n_docs from rows group by 1),
    w as (select *, {weights}[((row_number() over (order by source nulls last) - 1) % {len(WEIGHTS)} + 1)::INT]::BIGINT weight, source_size * {CAP} most from per),
    o as (select *, (sum(source_size) over ()) * {SHARE_PERCENT / 100}::DOUBLE pool,
          coalesce(sum(most) over (order by most / weight, source nulls last rows between unbounded preceding and 1 preceding), 0) before,
          sum(weight) over (order by most / weight, source nulls last rows between current row and unbounded following) onward from w),
    c as (select *, most * onward <= (pool - before) * weight held from o),
    t as (select *, case when held then most::DOUBLE else (weight * (pool - sum(case when held then most else 0 end) over ()))::DOUBLE / sum(case when held then 0 else weight end) over () end target from c),
    targets as (select source, source_size, n_docs, target, round(target)::BIGINT words from t),
    total as (select round(sum(words) / {block})::BIGINT seats from targets),
    won as (select source, 1 seat from targets, total, lateral (select unnest(range(seats)) k) where words > 0
            qualify row_number() over (order by words / (2 * k + 1) desc, source nulls last) <= any_value(seats) over ()),
    blocks as (select t.source, any_value(words) words, count(won.seat) quota, any_value(target) target,
               any_value(source_size) source_size, any_value(ceil(n_docs / {shard_rows})::BIGINT) shards from targets t left join won on t.source is not distinct from won.source group by 1),
    placed as (select r.*, b.source_size, b.target, r.k % b.shards shard from rows r join blocks b on r.source is not distinct from b.source),
    sh as (select p.source, shard, sum(size)::BIGINT shard_size from placed p group by 1, 2),
    shb as (select sh.*, b.words, b.quota from sh join blocks b on sh.source is not distinct from b.source),
    won2 as (select source, shard from shb, lateral (select unnest(range(quota)) k) where shard_size > 0
             qualify row_number() over (partition by source order by shard_size / (2 * k + 1) desc, shard) <= any_value(quota) over (partition by source)),
    q as (select shb.source, shb.shard, any_value(shard_size) shard_size, any_value(words) words, count(won2.shard) quota
          from shb left join won2 on shb.source is not distinct from won2.source and shb.shard = won2.shard group by 1, 2),
    f as (select *, least(quota * {block}, shard_size * {CAP}) first, words - sum(least(quota * {block}, shard_size * {CAP})) over (partition by source) more from q),
    g as (select *, case when more >= 0 then shard_size * {CAP} - first else first end room from f),
    takes as (select source, shard, shard_size, (first + sign(more) * greatest(0, least(room, abs(more) - coalesce(sum(room) over (partition by source order by shard rows between unbounded preceding and 1 preceding), 0))))::BIGINT take from g),
    run as (select p.*, sum(size) over (partition by p.source, p.shard order by k, doc_id, size rows unbounded preceding)::BIGINT upto, shard_size, take, shard_size // {block} n,
            case when shard_size > 0 then take // shard_size else 0 end passes from placed p join takes x on p.source is not distinct from x.source and p.shard = x.shard),
    z as (select *, upto - size since, take - passes * shard_size rest, {key("coalesce(source, '-') || ':' || shard || ':turn'")} % greatest(n, 1) turn,
          list_value({', '.join(map(str, STRIDE))})[1 + {key("coalesce(source, '-') || ':' || shard || ':stride'")} % {STRIDES}] stride from run),
    parts as (select doc_id, sum(greatest(0, least(upto, b * {block} + greatest(0, least({block}, rest - {block} * (case when b < n then (b * (stride % greatest(n, 1)) + turn) % greatest(n, 1) else n end)))) - greatest(since, b * {block}))) words
              from z, lateral (select unnest(range(since // {block}, (upto - 1) // {block} + 1)) b) where size > 0 group by 1)
    select z.doc_id, size, source_size, target, (passes * size + coalesce(words, 0))::BIGINT taken from z left join parts on z.doc_id = parts.doc_id"""
