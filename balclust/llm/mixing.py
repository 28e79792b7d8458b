"""Mixing sources to target weights, block by block.

Each source's texts, in order, form one stream of words cut into blocks of fixed length. Every
output shard draws how many blocks of each source it gets; the draws are multinomial, given
that all shards together take a source's target to the word. The k-th draw of a source is the block at
the k-th place of that source's pseudorandom index permutation (a new one for each pass over the source; the
short last block comes last), and joins the texts that the block covers by its index. The permutation is a keyed
swap-or-not shuffle: in each round an index and its mirror image about the round's key change places if a coin that both share
says so, which is a bijection for any number of blocks.

All is DataFrame work: no text moves, no source lies in one task (a source's running totals are taken
in buckets of a hash of doc_id, whose number grows with the rows, and then over the buckets), and drawn blocks are dealt out in runs.

Defined cases: a null or blank text has size 0 and nothing of it is taken; a null source is a source, the
last; rows alike in doc_id and size follow each other by a hash of the text; repeated rows each get their row and their own share; a
text of any length is a number of words and the blocks that these cover; an empty table gives an empty result; other columns, of whatever name, are ignored
or, where rows are given back, come back as they were.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from . import common

WEIGHTS, MOST = (5, 2, 1), 3
#: Words in a block, blocks in an output shard on average, draws made by one row.
BLOCK, SHARD_BLOCKS, RUN = 1024, 4096, 65_536
#: The least number of buckets, and rows that a bucket holds on average beyond it.
BUCKETS, BUCKET_ROWS = 1024, 100_000
#: Rounds of a permutation, and the prime of the rounds' coins.
ROUNDS, FIELD = 24, (1 << 31) - 1
SPACE = r"\x20\x09-\x0D"


def word_count(text: Column) -> Column:
    return F.size(F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(f"[^{SPACE}]+"), F.lit(0))).cast("long")


def _key(source: Column) -> Column:
    """A source's name as a key without null that sorts by code point, null last."""
    return F.when(source.isNull(), "t").otherwise(F.concat(F.lit("s"), source))


def targets(sizes: DataFrame) -> DataFrame:
    """source_key, source_size, place, target of sizes (source_key, source_size); one row per source is all that is sorted here.

    In order of cap per weight the sources are filled up; from the first whose cap holds its share on, all get the same level per weight.
    """
    everything = W.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    named = sizes.withColumn("place", F.row_number().over(W.orderBy("source_key")).cast("long") - 1)
    named = named.withColumn("weight", F.element_at(F.array(*map(F.lit, WEIGHTS)), (F.col("place") % len(WEIGHTS) + 1).cast("int")).cast("long")).withColumn("cap", F.col("source_size") * MOST)
    order = W.orderBy(F.col("cap") / F.col("weight"), "place")
    filled = (
        named.withColumn("rest", F.sum("source_size").over(everything) - F.coalesce(F.sum("cap").over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
        .withColumn("open", F.sum("weight").over(order.rowsBetween(0, W.unboundedFollowing)))
        .withColumn("level", F.when(F.col("cap") * F.col("open") >= F.col("weight") * F.col("rest"), F.col("rest") / F.col("open")))
        .withColumn("level", F.max("level").over(everything))
    )
    return filled.select("source_key", "source_size", "place", F.least(F.col("cap").cast("double"), F.col("weight") * F.col("level")).alias("target"))


def _number(*parts: str) -> str:
    """SQL of a whole number made of the parts: the first 48 bits of an MD5."""
    return f"conv(substring(md5(concat_ws(':', {', '.join(parts)})), 1, 12), 16, 10)"


def bucket(doc_id: Column, buckets: int) -> Column:
    """The bucket of a row: by a hash, so that neither steps nor nulls among the ids crowd one."""
    return (F.conv(F.substring(F.md5(F.coalesce(doc_id.cast("string"), F.lit(""))), 1, 12), 16, 10).cast("long") % buckets).cast("long")


def draws(sources: DataFrame, block: int = BLOCK) -> DataFrame:
    """source_key, shard, index (of the block), taken (words from its start), whole: one row per block drawn. sources: as targets gives."""
    each = (
        sources.where("source_size > 0 AND target > 0")
        .withColumn("words", F.least(F.col("source_size") * MOST, F.floor(F.col("target") + 0.5)))
        .withColumn("full", F.floor(F.col("source_size") / block)).withColumn("tail", F.col("source_size") % block)
        .withColumn("blocks", F.col("full") + (F.col("tail") > 0).cast("long"))
        .withColumn("passes", F.expr("words div source_size")).withColumn("left", F.col("words") % F.col("source_size"))
        .withColumn("n", F.col("passes") * F.col("blocks") + F.expr(f"(left + {block - 1}) div {block}"))
        # Keys of all rounds of all passes (MOST + 1 at most): about what a round mirrors, and the factor and the summand of its coin.
        .withColumn("mirror", F.expr(f"transform(sequence(0, {(MOST + 1) * ROUNDS - 1}), i -> cast({_number("'mirror'", 'place', 'i')} as long) % greatest(full, 1L))"))
        .withColumn("factor", F.expr(f"transform(sequence(0, {(MOST + 1) * ROUNDS - 1}), i -> cast({_number("'factor'", 'place', 'i')} as long) % {FIELD - 1} + 1)"))
        .withColumn("summand", F.expr(f"transform(sequence(0, {(MOST + 1) * ROUNDS - 1}), i -> cast({_number("'summand'", 'place', 'i')} as long) % {FIELD})"))
        .withColumn("shards", F.expr(f"(sum(n) OVER () + {SHARD_BLOCKS - 1}) div {SHARD_BLOCKS}"))
    )
    runs = each.where("n > 0").withColumn("run", F.explode(F.expr(f"sequence(0L, (n - 1) div {RUN})"))).repartition("source_key", "run")
    at, image = f"cast(pass as int) * {ROUNDS} + r", f"pmod(mirror[cast(pass as int) * {ROUNDS} + r] - x, full)"
    shuffle = f"aggregate(sequence(0, {ROUNDS - 1}), j, (x, r) -> IF((greatest(x, {image}) % {FIELD} * factor[{at}] + summand[{at}]) % {FIELD} % 2 = 1, {image}, x))"
    one = runs.withColumn("k", F.explode(F.expr(f"sequence(run * {RUN}, least(n, (run + 1) * {RUN}) - 1)")))
    return (
        one.withColumn("pass", F.expr("k div blocks")).withColumn("j", F.col("k") % F.col("blocks"))
        .withColumn("index", F.when(F.col("j") < F.col("full"), F.expr(shuffle)).otherwise(F.col("full")))
        .withColumn("length", F.when(F.col("j") < F.col("full"), F.lit(block).cast("long")).otherwise(F.col("tail")))
        .withColumn("taken", F.when(F.col("pass") < F.col("passes"), F.col("length")).otherwise(F.least("length", F.col("left") - F.col("j") * block)))
        .withColumn("shard", F.conv(F.substring(F.md5(F.concat_ws(":", "place", "k")), 1, 12), 16, 10).cast("long") % F.col("shards"))
        .select("source_key", "shard", "index", "taken", (F.col("taken") == F.col("length")).alias("whole"))
    )


def shard_counts(drawn: DataFrame) -> DataFrame:
    """How many blocks of each source each shard draws."""
    return drawn.groupBy("shard", "source_key").agg(F.count("*").alias("n_blocks"), F.sum("taken").alias("n_words"))


def drawn_rows(docs: DataFrame, block: int = BLOCK) -> DataFrame:
    """doc_id, source_key, tie, size, source_size, target, taken, first_shard and drawn of each row of docs (doc_id, text, source). tie: a hash of the text.

    drawn: the row's words from low to high that a block covers, how many times they are taken, and the end of what is taken of them once more.
    """
    rows = common.stage(docs.select("doc_id", _key(F.col("source")).alias("source_key"), word_count(F.col("text")).alias("size"), F.xxhash64("text").alias("tie")))
    rows = rows.withColumn("bucket", bucket(F.col("doc_id"), max(BUCKETS, rows.count() // BUCKET_ROWS)))
    buckets = rows.groupBy("source_key", "bucket").agg(F.sum("size").alias("words"))
    sources = common.stage(targets(buckets.groupBy("source_key").agg(F.sum("words").alias("source_size"))))
    before = W.partitionBy("source_key").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)
    buckets = buckets.withColumn("base", F.coalesce(F.sum("words").over(before), F.lit(0))).join(sources.select("source_key", "source_size", "target"), "source_key").drop("words")
    inside = W.partitionBy("source_key", "bucket").orderBy("doc_id", "size", "tie").rowsBetween(W.unboundedPreceding, -1)
    set_out = rows.withColumn("start", F.coalesce(F.sum("size").over(inside), F.lit(0))).join(buckets.hint("merge"), ["source_key", "bucket"]).withColumn("start", F.col("start") + F.col("base"))

    taken = draws(sources, block).groupBy("source_key", "index").agg(F.sum(F.col("whole").cast("long")).alias("times"), F.max(F.when(~F.col("whole"), F.col("taken"))).alias("part"), F.min("shard").alias("shard"))
    parts = set_out.where("size > 0").withColumn("index", F.explode(F.expr(f"sequence(start div {block}, (start + size - 1) div {block})")))
    parts = parts.withColumn("low", F.greatest("start", F.col("index") * block)).withColumn("high", F.least(F.col("start") + F.col("size"), (F.col("index") + 1) * block))
    # Both sides grow with the corpus: neither is broadcast.
    met = parts.join(taken.hint("merge"), ["source_key", "index"], "left").withColumn(
        "part_taken", F.coalesce("times", F.lit(0)) * (F.col("high") - F.col("low")) + F.greatest(F.lit(0), F.least(F.col("high"), F.col("index") * block + F.coalesce("part", F.lit(0))) - F.col("low"))
    )
    keys = ["source_key", "start", "doc_id", "tie", "size", "source_size", "target"]
    met = met.withColumns({"from": F.col("low") - F.col("start"), "to": F.col("high") - F.col("start"), "times": F.coalesce("times", F.lit(0))})
    met = met.withColumn("more", F.greatest("from", F.least("to", F.col("index") * block + F.coalesce("part", F.lit(0)) - F.col("start"))))
    drawn = F.collect_list(F.when(F.col("part_taken") > 0, F.struct("from", "to", "times", "more"))).alias("drawn")
    summed = met.groupBy(*keys).agg(F.sum("part_taken").alias("taken"), F.min(F.when(F.col("part_taken") > 0, F.col("shard"))).alias("first_shard"), drawn)
    blank = set_out.where("size = 0").select(*keys, F.lit(0).cast("long").alias("taken"), F.lit(None).cast("long").alias("first_shard"), F.lit(None).alias("drawn"))
    return summed.unionByName(blank).drop("start")


def mixture(docs: DataFrame, block: int = BLOCK) -> DataFrame:
    """doc_id, source_key, tie, size, source_size, target, taken, first_shard of each row of docs (doc_id, text, source). tie: a hash of the text."""
    return drawn_rows(docs, block).drop("drawn")


def op8(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixture(common.documents(spark, sf_dir)).select("doc_id", "size", "source_size", "target", "taken", "first_shard")


def _sql_rounds() -> str:
    """The rounds of the shuffle, one step each: x becomes its mirror image y where the coin of the larger of both is odd."""

    def number(what: str, r: int) -> str:
        return f"CAST('0x' || substr(md5('{what}:' || place || ':' || ((t // blocks) * {ROUNDS} + {r})), 1, 12) AS BIGINT)"

    steps = ["turn0 AS (SELECT *, t % blocks AS x FROM drawn)"]
    for r in range(ROUNDS):
        mirrored = f"SELECT *, (({number('mirror', r)} % greatest(nfull, 1) - x) % greatest(nfull, 1) + greatest(nfull, 1)) % greatest(nfull, 1) AS y FROM turn{r}"
        coin = f"(greatest(x, y) % {FIELD} * ({number('factor', r)} % {FIELD - 1} + 1) + {number('summand', r)} % {FIELD}) % {FIELD} % 2"
        steps.append(f"turn{r + 1} AS (SELECT * EXCLUDE (x, y), CASE WHEN {coin} = 1 THEN y ELSE x END AS x FROM ({mirrored}))")
    return ",\n".join(steps)


OP8_SQL = f"""WITH rows AS (
  SELECT doc_id, CASE WHEN source IS NULL THEN 't' ELSE 's' || source END AS k, len(regexp_extract_all(coalesce(text, ''), '[^{SPACE}]+'))::BIGINT AS size FROM documents),
sized AS (SELECT k, sum(size)::BIGINT AS source_size, row_number() OVER (ORDER BY k) - 1 AS place FROM rows GROUP BY k),
weighed AS (SELECT *, CASE place % 3 WHEN 0 THEN 5 WHEN 1 THEN 2 ELSE 1 END AS w, 3 * source_size AS cap FROM sized),
filled AS (SELECT *, (sum(source_size) OVER () - coalesce(sum(cap) OVER (ORDER BY cap / w, place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::BIGINT AS rest,
  (sum(w) OVER (ORDER BY cap / w, place ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))::BIGINT AS open FROM weighed),
sources AS (SELECT k, source_size, place, least(cap::DOUBLE, w * max(CASE WHEN cap * open >= w * rest THEN rest / open END) OVER ()) AS target FROM filled),
counted AS (SELECT *, least(3 * source_size, floor(target + 0.5)::BIGINT) AS words, source_size // {BLOCK} AS nfull, source_size % {BLOCK} AS tail FROM sources WHERE source_size > 0 AND target > 0),
planned AS (SELECT *, nfull + (tail > 0)::BIGINT AS blocks, words // source_size AS passes, words % source_size AS rem,
  (words // source_size) * (nfull + (tail > 0)::BIGINT) + (words % source_size + {BLOCK - 1}) // {BLOCK} AS n FROM counted),
sharded AS (SELECT *, ((sum(n) OVER ())::BIGINT + {SHARD_BLOCKS - 1}) // {SHARD_BLOCKS} AS shards FROM planned),
drawn AS (SELECT *, unnest(range(0, n)) AS t FROM sharded),
{_sql_rounds()},
slots AS (SELECT k, CASE WHEN t % blocks < nfull THEN x ELSE nfull END AS idx,
  CASE WHEN t % blocks < nfull THEN {BLOCK} ELSE tail END AS length, t // blocks < passes AS early, rem - (t % blocks) * {BLOCK} AS room,
  CAST('0x' || substr(md5(place || ':' || t), 1, 12) AS BIGINT) % shards AS shard FROM turn{ROUNDS}),
takes AS (SELECT k, idx, sum((early OR room >= length)::BIGINT)::BIGINT AS times, max(CASE WHEN NOT early AND room < length THEN room END) AS part, min(shard) AS shard FROM slots GROUP BY k, idx),
laid AS (SELECT *, row_number() OVER () AS r, coalesce(sum(size) OVER (PARTITION BY k ORDER BY CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 12) AS BIGINT) % (SELECT greatest({BUCKETS}, count(*) // {BUCKET_ROWS}) FROM rows), doc_id NULLS FIRST, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS start FROM rows),
parts AS (SELECT *, unnest(range(start // {BLOCK}, (start + size - 1) // {BLOCK} + 1)) AS idx FROM laid WHERE size > 0),
met AS (SELECT r, parts.idx, coalesce(times, 0) * (least(start + size, (idx + 1) * {BLOCK}) - greatest(start, idx * {BLOCK}))
  + greatest(0, least(start + size, idx * {BLOCK} + coalesce(part, 0)) - greatest(start, idx * {BLOCK})) AS got, shard FROM parts LEFT JOIN takes USING (k, idx)),
summed AS (SELECT r, sum(got)::BIGINT AS taken, min(CASE WHEN got > 0 THEN shard END) AS first_shard FROM met GROUP BY r)
SELECT doc_id, size, source_size, target, coalesce(taken, 0)::BIGINT AS taken, first_shard FROM laid JOIN sources USING (k) LEFT JOIN summed USING (r)"""


def words_of(text: Column, ranges: Column) -> Column:
    """The words of the text in the ranges (from, to), with the white space between them; a range begins where the one before ends or later."""
    parts = F.split(F.regexp_replace(text, f"^[{SPACE}]+", ""), f"(?<=[{SPACE}])(?=[^{SPACE}])")
    held = F.flatten(F.transform(ranges, lambda r: F.slice(parts, (r["from"] + 1).cast("int"), (r["to"] - r["from"]).cast("int"))))
    return F.regexp_replace(F.array_join(held, ""), f"[{SPACE}]+$", "")


def apply(docs: DataFrame, block: int = BLOCK) -> DataFrame:
    """docs mixed: each row as often as it is taken whole, and once more cut to the words that the last pass has drawn; rows that nothing is taken of go.

    The row travels as one struct, so that no column of docs meets one of ours. n_chars follows the text where docs has it.
    """
    copy = W.partitionBy("doc_id", "source_key", "tie").orderBy("size")
    planned = drawn_rows(docs, block).where("taken > 0").select("doc_id", "source_key", "tie", "size", F.sort_array("drawn").alias("drawn")).withColumn("copy", F.row_number().over(copy))
    texts = common.as_row(docs).select("row", F.col("row.doc_id").alias("id"), _key(F.col("row.source")).alias("key"), F.xxhash64("row.text").alias("hash"))
    texts = texts.withColumn("place", F.row_number().over(W.partitionBy("id", "key", "hash").orderBy(F.xxhash64("row"))))
    same = F.col("doc_id").eqNullSafe(F.col("id")) & (F.col("source_key") == F.col("key")) & (F.col("tie") == F.col("hash")) & (F.col("copy") == F.col("place"))
    met = texts.join(planned.hint("merge"), same)
    each = met.withColumn("turn", F.explode(F.expr("sequence(1L, array_max(transform(drawn, d -> d.times + IF(d.more > d.from, 1L, 0L))))")))
    each = each.withColumn("ranges", F.expr("transform(filter(drawn, d -> d.times >= turn OR (d.times = turn - 1 AND d.more > d.from)), d -> struct(d.from AS from, IF(d.times >= turn, d.to, d.more) AS to))"))
    whole = F.expr("aggregate(ranges, 0L, (n, r) -> n + r.to - r.from)") == F.col("size")
    text = F.when(whole, F.col("row.text")).otherwise(words_of(F.col("row.text"), F.col("ranges")))
    cut = each.select(F.col("row"), text.alias("text"))
    return common.from_row(cut, docs.columns, text=F.col("text"), n_chars=F.length("text").cast("long"))
