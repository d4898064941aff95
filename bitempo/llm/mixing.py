"""Mixing sources to target weights, with DataFrame functions alone.

Every source's words are one line, cut into blocks of ``block`` words; documents lie on it in the order of a hash of their ids. The
mix is a row of output slots of one block each, in shards of ``shard`` slots. Each slot of a shard draws its source with the sources'
shares as probabilities, so a shard's counts are multinomial. A source's slots are numbered on through the shards; number j is filled by
block P(j mod n) of its n blocks, where P is the pseudorandom permutation that belongs to epoch j div n.

A permutation is a function of the index, so nothing is sorted or ranked: a Feistel network over two parts of the index, whose product
of sizes is the least that holds n, with keys from a hash of source, epoch and round; what falls beyond n goes through it again. Slots
meet the documents' blocks by the block's index. The places of documents on a source's line are ranks by a hash of their ids, found in two steps
(within one of 4,096 hash ranges, plus what lies before that range), so that no window holds all documents of a source.

Targets: sources in code-point order, null last, weigh 1, 2, 3 in turn; each gets its share of all words, but at most ``most`` = 3 times
its own, and what is left over is shared again by weight. All draws and permutations depend on the data and ``seed`` alone.

Cases: a null text or source is no words and a source of its own; documents without words are never taken; ties of doc_id are ordered by size;
repeated rows are separate documents; an empty table gives an empty one; a source's slots beyond ``most`` epochs
are left out, so nothing is repeated more often; other columns are ignored. Windows without a key are over rows of sources, one for each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stash

WORDS = r"[^\x20\x09-\x0D]+"
BLOCK, SHARD, MOST, CELLS, ROUNDS, SEED = 32, 1 << 16, 3, 4096, 6, "mix-1"
FEW_SPANS = 100_000  # rows of four longs that are broadcast; more are met by a shuffle
FACTOR, WRAP = 73_244_475, 1 << 31  # of the rounds of a permutation


def keyed(*parts: str | Column, seed: str = SEED) -> Column:
    """60 bits of the md5 of the seed and the parts' decimal text."""
    text = F.concat_ws("|", F.lit(seed), *[F.coalesce(F.col(p) if isinstance(p, str) else p, F.lit(-1)).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")


def _range_of(key: Column) -> Column:
    """Which of 4,096 equal ranges of 60 bits."""
    return F.shiftright(key, 48).cast("int")


def document_sizes(docs: DataFrame) -> DataFrame:
    """(doc_id, source, size): words of each whole text."""
    return docs.select("doc_id", "source", F.coalesce(F.regexp_count("text", F.lit(WORDS)), F.lit(0)).cast("long").alias("size"))


def source_targets(sizes: DataFrame, block: int = BLOCK, most: int = MOST) -> DataFrame:
    """One row for each source: no, source, source_size, weight, target, blocks, share (thousandths of a slot that it should get)."""
    sums = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    by_name = Window.orderBy(F.col("source").isNull(), "source")
    numbered = sums.withColumn("no", (F.row_number().over(by_name) - 1).cast("long")).withColumn("weight", F.col("no") % 3 + 1)
    # the water level: sources by what they can give for their weight; the first that is not used up sets it for all after it
    by_room = Window.orderBy(F.col("source_size") / F.col("weight"), "no")
    wide = lambda c: c.cast("decimal(38,0)")
    filled = (
        numbered.withColumn("total", F.sum("source_size").over(Window.partitionBy()))
        .withColumn("given", F.coalesce(F.sum(F.lit(most) * F.col("source_size")).over(by_room.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
        .withColumn("weights", F.sum("weight").over(by_room.rowsBetween(Window.currentRow, Window.unboundedFollowing)))
        .withColumn("free", wide(F.lit(most) * F.col("source_size")) * wide(F.col("weights")) >= wide(F.col("weight")) * wide(F.col("total") - F.col("given")))
        .withColumn("level", F.min(F.when(F.col("free"), F.col("given"))).over(Window.partitionBy()))
        .withColumn("sharing", F.max(F.when(F.col("free"), F.col("weights"))).over(Window.partitionBy()))
    )
    even = (F.col("total") - F.col("level")) * F.col("weight") / F.col("sharing").cast("double")
    target = F.when(F.col("free"), F.least(even, (F.lit(most) * F.col("source_size")).cast("double"))).otherwise((F.lit(most) * F.col("source_size")).cast("double"))
    return (
        filled.withColumn("target", F.coalesce(target, F.lit(0.0)))
        .withColumn("blocks", F.ceil(F.col("source_size") / F.lit(block)).cast("long"))
        .withColumn("share", F.when(F.col("source_size") > 0, F.floor(F.col("target") * F.col("blocks") * 1000 / F.col("source_size"))).otherwise(0).cast("long"))
        .select("no", "source", "source_size", "weight", "target", "blocks", "share")
    )


def _mixed_up(x: Column, key: Column) -> Column:
    """31 bits from 31 bits and a key."""
    x = (x.bitwiseXOR(key) * F.lit(FACTOR)) % WRAP
    x = (x.bitwiseXOR(F.shiftright(x, 15)) * F.lit(FACTOR)) % WRAP
    return x.bitwiseXOR(F.shiftright(x, 13))


def shard_counts(sources: DataFrame, shard: int = SHARD) -> DataFrame:
    """(shard, no, slots): multinomial source counts of each output shard, one draw for each slot."""
    everything = Window.partitionBy()
    before = Window.orderBy("no").rowsBetween(Window.unboundedPreceding, -1)
    held = sources.where("share > 0").select("no", "share").withColumn("all_shares", F.sum("share").over(everything))
    held = held.withColumn("low", F.coalesce(F.sum("share").over(before), F.lit(0))).withColumn("width", F.expr(f"all_shares div {CELLS} + 1"))
    held = held.withColumn("slots", F.expr("(all_shares + 500) div 1000"))
    # sources are found by cells of their cumulated shares: a row for each source and cell that meet, so their number plus CELLS at most
    spans = stash(held.select("no", "low", (F.col("low") + F.col("share")).alias("high"), F.explode(F.expr("sequence(low div width, (low + share - 1) div width)")).alias("cell")), "spans")
    shards = held.select("all_shares", "width", "slots").distinct().withColumn("shard", F.explode(F.expr(f"sequence(0L, (slots + {shard - 1}) div {shard} - 1)"))).repartition(_tasks(sources), "shard")
    # a draw is 62 bits of arithmetic on the slot's number with two keys of its shard, which makes no strings to collect
    shards = shards.withColumn("high", keyed("shard", F.lit(0)) % WRAP).withColumn("low", keyed("shard", F.lit(1)) % WRAP)
    draws = shards.withColumn("draw", F.explode(F.expr(f"sequence(0L, least({shard}L, slots - shard * {shard}) - 1)")))
    draws = draws.withColumn("high", _mixed_up(F.col("draw"), F.col("high"))).withColumn("low", _mixed_up(F.col("draw"), F.col("low")))
    draws = draws.withColumn("at", (F.col("high") * WRAP + F.col("low")) % F.col("all_shares"))
    # the spans alone may be broadcast, and only when counted; the planner knows no size of what is exploded
    spans = spans.hint("broadcast" if spans.count() <= FEW_SPANS else "merge")
    drawn = draws.select("shard", "at", F.expr("at div width").alias("cell")).join(spans, "cell").where("at >= low and at < high")
    return drawn.groupBy("shard", "no").agg(F.count(F.lit(1)).alias("slots"))


def _before(df: DataFrame, by: list[str], value: str, name: str) -> DataFrame:
    """Running sum of ``value`` before each row of small groups."""
    window = Window.partitionBy(*by[:-1]).orderBy(by[-1]).rowsBetween(Window.unboundedPreceding, -1)
    return df.withColumn(name, F.coalesce(F.sum(value).over(window), F.lit(0)))


def _parts(n: Column) -> tuple[Column, Column]:
    """Sizes of the two parts of an index below ``n``."""
    rows = F.ceil(F.sqrt(n.cast("double"))).cast("long")
    return rows, _whole(n + rows - 1, rows)


def _whole(a: Column, b: Column) -> Column:
    return ((a - a % b) / b).cast("long")


def _walked(index: Column, n: Column, keys: Column) -> Column:
    """The index below ``n`` that the network comes to when it goes on from one that is not."""
    rows, columns = _parts(n)

    def turn(s: Column, key: Column) -> Column:
        # the parts change places each round, and their sizes with them
        return F.struct(s["y"].alias("x"), ((s["x"] + _mixed_up(s["y"], key)) % s["of_x"]).alias("y"), s["of_y"].alias("of_x"), s["of_x"].alias("of_y"))

    def once(i: Column) -> Column:
        parts = F.struct(_whole(i, columns).alias("x"), (i % columns).alias("y"), rows.alias("of_x"), columns.alias("of_y"))
        return F.aggregate(keys, parts, turn, lambda s: s["x"] * columns + s["y"])

    # fewer than ``rows`` indexes lie beyond n, so a walk that leaves is back after so many steps
    return F.aggregate(F.sequence(F.lit(1).cast("long"), rows), index, lambda i, _: F.when(i < n, i).otherwise(once(i)))


def permuted(rows: DataFrame) -> DataFrame:
    """``rows(index, n, keys, …)`` with ``block``: the index below n that the permutation with one key for each round gives to ``index``.

    The rounds are columns one after the other, which compile to arithmetic; the few that come out beyond n walk on.
    """
    kept = [c for c in rows.columns if c not in ("index", "n", "keys")]
    a, b = _parts(F.col("n"))
    state = rows.withColumn("of_x", a).withColumn("of_y", b).withColumn("x", _whole(F.col("index"), F.col("of_y"))).withColumn("y", F.col("index") % F.col("of_y"))
    for r in range(ROUNDS):
        state = state.withColumn("g", (F.col("y").bitwiseXOR(F.get("keys", F.lit(r))) * F.lit(FACTOR)) % WRAP)
        state = state.withColumn("f", (F.col("g").bitwiseXOR(F.shiftright("g", 15)) * F.lit(FACTOR)) % WRAP)
        turned = (F.col("x") + F.col("f").bitwiseXOR(F.shiftright("f", 13))) % F.col("of_x" if r % 2 == 0 else "of_y")
        state = state.select(*kept, "n", "keys", "of_x", "of_y", F.col("y").alias("x"), turned.alias("y"))
    state = state.select(*kept, "n", "keys", (F.col("x") * F.col("of_y") + F.col("y")).alias("first"))
    return state.select(*kept, F.when(F.col("first") < F.col("n"), F.col("first")).otherwise(_walked(F.col("first"), F.col("n"), F.col("keys"))).alias("block"))


def _tasks(df: DataFrame) -> int:
    """Tasks that make rows out of few: small inputs would be gathered in one task otherwise."""
    return 4 * df.sparkSession.sparkContext.defaultParallelism


def mix_slots(counts: DataFrame, sources: DataFrame, most: int = MOST) -> DataFrame:
    """(shard, no, epoch, block): the slots of every shard with the block of the source that fills them."""
    keys = F.transform(F.sequence(F.lit(0), F.lit(most - 1)), lambda e: F.transform(F.sequence(F.lit(0), F.lit(ROUNDS - 1)), lambda r: keyed("no", e, r) % WRAP))
    numbered = _before(counts, ["no", "shard"], "slots", "first").join(sources.select("no", "blocks", keys.alias("keys")), "no")
    # a source's shards are dealt out before its slots are made, so that no task makes all slots of a source
    numbered = numbered.repartition(_tasks(counts), "no", "shard")
    slots = numbered.select("shard", "no", "blocks", "keys", F.explode(F.expr("sequence(first, first + slots - 1)")).alias("j")).where(F.expr(f"j div blocks < {most}"))
    slots = slots.withColumn("epoch", F.expr("j div blocks"))
    return permuted(slots.select("shard", "no", "epoch", (F.col("j") % F.col("blocks")).alias("index"), F.col("blocks").alias("n"), F.get("keys", F.col("epoch").cast("int")).alias("keys")))


def place_documents(sizes: DataFrame, sources: DataFrame) -> DataFrame:
    """(doc_id, no, source_size, target, size, start): where each document's words begin on its source's line."""
    known = sizes.join(sources.select(F.col("source").alias("its"), "no", "source_size", "target"), F.col("source").eqNullSafe(F.col("its")))
    known = known.select("doc_id", "no", "source_size", "target", "size", _range_of(keyed("doc_id")).alias("part"))
    sums = known.groupBy("no", "part").agg(F.sum("size").alias("held"))
    starts = _before(sums, ["no", "part"], "held", "base").select("no", "part", "base")
    inside = Window.partitionBy("no", "part").orderBy("doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    placed = known.withColumn("inner", F.coalesce(F.sum("size").over(inside), F.lit(0))).join(starts, ["no", "part"])
    return placed.select("doc_id", "no", "source_size", "target", "size", (F.col("base") + F.col("inner")).alias("start"))


def mixed(docs: DataFrame, block: int = BLOCK, shard: int = SHARD, most: int = MOST, keep_source: bool = False) -> DataFrame:
    """(doc_id, size, source_size, target, taken, copies[, source]) for every row of ``docs(doc_id, text, source)``.

    ``taken`` counts the words that the mix takes of a document, ``copies`` how often it takes the document's first word.
    """
    sizes = stash(document_sizes(docs), "sizes")
    sources = stash(source_targets(sizes, block, most), "sources")
    placed = stash(place_documents(sizes, sources), "placed")
    # a document's blocks, with the words of it that each holds
    parts = placed.where("size > 0").withColumn("block", F.explode(F.expr(f"sequence(start div {block}, (start + size - 1) div {block})")))
    parts = parts.withColumn("words", F.expr(f"least(start + size, (block + 1) * {block}) - greatest(start, block * {block})"))
    counts = stash(shard_counts(sources, shard), "counts")
    # stored, as a join's test for nulls would be pushed through the rounds of the permutation and grow with each
    times = stash(mix_slots(counts, sources, most).groupBy("no", "block").agg(F.count(F.lit(1)).alias("times")), "times")
    # sizes of exploded rows are unknown to the planner, which would broadcast them: these joins are by shuffle
    taken = (
        parts.join(times.hint("merge"), ["no", "block"])
        .groupBy("no", "start")
        .agg(F.sum(F.col("words") * F.col("times")).alias("taken"), F.max(F.when(F.expr(f"block = start div {block}"), F.col("times"))).alias("copies"))
    )
    found = placed.where("size > 0").join(taken.hint("merge"), ["no", "start"], "left").unionByName(placed.where("size = 0").withColumns({"taken": F.lit(None).cast("long"), "copies": F.lit(None).cast("long")}))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c)
    found = found.join(sources.select("no", "source"), "no") if keep_source else found
    return found.select("doc_id", "size", "source_size", "target", zero("taken"), zero("copies"), *(["source"] if keep_source else []))


def mixed_documents(docs: DataFrame, block: int = BLOCK, shard: int = SHARD, most: int = MOST) -> DataFrame:
    """The rows of ``docs`` as often as the mix takes their first word, with all columns.

    Rows that agree in id, source and size share their copies evenly, rounded down.
    """
    taken = mixed(docs, block, shard, most, keep_source=True).groupBy("doc_id", "source", "size").agg(F.sum("copies").alias("copies"), F.count(F.lit(1)).alias("rows"))
    taken = taken.select(F.col("doc_id").alias("its_id"), F.col("source").alias("its_source"), F.col("size").alias("its_size"), F.expr("copies div rows").cast("int").alias("copies")).where("copies > 0")
    rows = docs.select(F.struct("*").alias("row"), "doc_id", "source", F.coalesce(F.regexp_count("text", F.lit(WORDS)), F.lit(0)).cast("long").alias("size"))
    same = F.col("doc_id").eqNullSafe(F.col("its_id")) & F.col("source").eqNullSafe(F.col("its_source")) & (F.col("size") == F.col("its_size"))
    return rows.join(stash(taken, "taken").hint("merge"), same).select("row", F.explode(F.expr("array_repeat(0, copies)"))).select("row.*")


#: The same mix in DuckDB SQL.
ORACLE = f"""
WITH RECURSIVE sizes AS (
  SELECT doc_id, source, CAST(coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0) AS BIGINT) AS size FROM documents),
sums AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM sizes GROUP BY source),
numbered AS (
  SELECT *, row_number() OVER (ORDER BY source IS NULL, source) - 1 AS no, (row_number() OVER (ORDER BY source IS NULL, source) - 1) % 3 + 1 AS weight FROM sums),
filled AS (
  SELECT *, CAST(sum(source_size) OVER () AS BIGINT) AS total,
    CAST(coalesce(sum({MOST} * source_size) OVER (ORDER BY source_size / CAST(weight AS DOUBLE), no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS given,
    CAST(sum(weight) OVER (ORDER BY source_size / CAST(weight AS DOUBLE), no ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS BIGINT) AS weights FROM numbered),
free AS (SELECT *, CAST({MOST} * source_size AS HUGEINT) * weights >= CAST(weight AS HUGEINT) * (total - given) AS free FROM filled),
levels AS (SELECT *, min(given) FILTER (free) OVER () AS level, max(weights) FILTER (free) OVER () AS sharing FROM free),
targets AS (
  SELECT no, source, source_size, weight,
    coalesce(CASE WHEN free THEN least(CAST((total - level) * weight AS DOUBLE) / CAST(sharing AS DOUBLE), CAST({MOST} * source_size AS DOUBLE)) ELSE CAST({MOST} * source_size AS DOUBLE) END, 0.0) AS target,
    CAST(ceil(source_size / CAST({BLOCK} AS DOUBLE)) AS BIGINT) AS blocks FROM levels),
sources AS (
  SELECT *, CASE WHEN source_size > 0 THEN CAST(floor(target * blocks * 1000 / CAST(source_size AS DOUBLE)) AS BIGINT) ELSE 0 END AS share FROM targets),
held AS (
  SELECT no, blocks, share, CAST(sum(share) OVER () AS BIGINT) AS all_shares,
    CAST(coalesce(sum(share) OVER (ORDER BY no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS low FROM sources WHERE share > 0),
totals AS (SELECT DISTINCT all_shares, (all_shares + 500) // 1000 AS slots FROM held),
points AS (
  SELECT (xor(h2, h2 >> 13) * {WRAP} + xor(l2, l2 >> 13)) % all_shares AS pos
  FROM (
    SELECT all_shares, (xor(h1, h1 >> 15) * {FACTOR}) % {WRAP} AS h2, (xor(l1, l1 >> 15) * {FACTOR}) % {WRAP} AS l2
    FROM (
      SELECT all_shares, (xor(s % {SHARD}, CAST('0x' || substr(md5('{SEED}|' || s // {SHARD} || '|0'), 1, 15) AS BIGINT) % {WRAP}) * {FACTOR}) % {WRAP} AS h1,
        (xor(s % {SHARD}, CAST('0x' || substr(md5('{SEED}|' || s // {SHARD} || '|1'), 1, 15) AS BIGINT) % {WRAP}) * {FACTOR}) % {WRAP} AS l1
      FROM (SELECT all_shares, unnest(range(0, slots)) AS s FROM totals) x) y) z),
drawn AS (SELECT no, count(*) AS n FROM points JOIN held ON pos >= low AND pos < low + share GROUP BY no),
slots AS (
  SELECT d.no, j // s.blocks AS epoch, j % s.blocks AS place, s.blocks AS n, CAST(ceil(sqrt(CAST(s.blocks AS DOUBLE))) AS BIGINT) AS a
  FROM (SELECT no, unnest(range(0, n)) AS j FROM drawn) d JOIN sources s USING (no) WHERE j // s.blocks < {MOST}),
keys AS (
  SELECT no, epoch, round, CAST('0x' || substr(md5('{SEED}|' || no || '|' || epoch || '|' || round), 1, 15) AS BIGINT) % {WRAP} AS key
  FROM (SELECT no, unnest(range(0, {ROUNDS})) AS round, epoch FROM sources, (SELECT unnest(range(0, {MOST})) AS epoch) e) t),
walk(no, epoch, place, n, a, b, i, x, y) AS (
  SELECT no, epoch, place, n, a, (n + a - 1) // a, 0, place // ((n + a - 1) // a), place % ((n + a - 1) // a) FROM slots
  UNION ALL
  SELECT no, epoch, place, n, a, b, i + 1, y, (x + xor(f, f >> 13)) % CASE WHEN i % 2 = 0 THEN a ELSE b END
  FROM (
    SELECT *, (xor(g, g >> 15) * {FACTOR}) % {WRAP} AS f
    FROM (
      SELECT w.*, (xor(w.y, k.key) * {FACTOR}) % {WRAP} AS g FROM walk w JOIN keys k ON w.no = k.no AND w.epoch = k.epoch AND w.i % {ROUNDS} = k.round
      WHERE w.i = 0 OR w.i % {ROUNDS} != 0 OR w.x * w.b + w.y >= w.n) t) u),
times AS (
  SELECT no, x * b + y AS block, count(*) AS times FROM walk WHERE i > 0 AND i % {ROUNDS} = 0 AND x * b + y < n GROUP BY ALL),
placed AS (
  SELECT doc_id, no, source_size, target, size,
    CAST(coalesce(sum(size) OVER (PARTITION BY no ORDER BY CAST('0x' || substr(md5('{SEED}|' || coalesce(doc_id, -1)), 1, 15) AS BIGINT) >> 48, doc_id NULLS FIRST, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start
  FROM sizes JOIN (SELECT source AS its, no, source_size, target FROM sources) s ON source IS NOT DISTINCT FROM its),
parts AS (
  SELECT *, least(start + size, (block + 1) * {BLOCK}) - greatest(start, block * {BLOCK}) AS words
  FROM (SELECT *, unnest(range(start // {BLOCK}, (start + size - 1) // {BLOCK} + 1)) AS block FROM placed WHERE size > 0) t),
taken AS (SELECT no, start, CAST(sum(words * times) AS BIGINT) AS taken FROM parts JOIN times USING (no, block) GROUP BY no, start)
SELECT doc_id, size, source_size, target, CASE WHEN size > 0 THEN coalesce(taken, 0) ELSE 0 END AS taken
FROM placed LEFT JOIN taken USING (no, start)
"""
