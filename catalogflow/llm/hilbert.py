"""Operator 10: shards along a Hilbert curve through several metadata dimensions.

Each dimension is quantised to ``bits`` bits; the cell's place on the curve is computed bit level by bit level with a table
of turns (state and octant to digit and next state), inside the JVM. Sizes are summed per cell, at most 2 ** (bits x dimensions)
rows whatever the table holds; running totals over cells cut the curve into runs of about ``target`` characters, and a
cell that is larger than a run is cut by a hash of the id. So shards are found without a global sort; writing
them, one file each, sorts inside each shard. Neighbouring cells share shards, which makes minimum and maximum of every
dimension narrow per file.

Defined cases: null in a dimension is cell 0; null or negative size is 0; null ids hash as 'null'; ties lie in one cell; repeated rows
go to one shard; empty table: empty result. Extra columns aren't read by ``assign`` and are carried unchanged by ``write``, whatever
their names: the operator's own columns get underscores until they clash with none.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from catalogflow.llm.mixing import HASH
from catalogflow.llm.order import free_name, running_total
from catalogflow.session import broadcast_small, staged


def curve_tables(n: int) -> tuple[list[int], list[int]]:
    """(digit, next state), both indexed by state * 2**n + octant; a state is entry corner * n + direction."""
    size, mask = 1 << n, (1 << n) - 1
    turn = lambda x, k: ((x >> (k % n)) | (x << (n - k % n))) & mask if k % n else x
    gray = lambda i: i ^ (i >> 1)
    inverse = {gray(i): i for i in range(size)}
    trail = lambda i: (~i & (i + 1)).bit_length() - 1  # trailing ones
    corner = lambda w: 0 if w == 0 else gray(2 * ((w - 1) // 2))
    axis = lambda w: 0 if w == 0 else (trail(w - 1) if w % 2 == 0 else trail(w)) % n
    digit, follow = [], []
    for state in range(size * n):
        entry, way = divmod(state, n)
        for octant in range(size):
            w = inverse[turn(octant ^ entry, way + 1)]
            digit.append(w)
            follow.append((entry ^ turn(corner(w), n - (way + 1) % n)) * n + (way + axis(w) + 1) % n)
    return digit, follow


def hilbert_index(dims: list[Column], bits: int) -> Column:
    n = len(dims)
    digit, follow = (F.array(*[F.lit(x) for x in t]) for t in curve_tables(n))

    def step(acc: Column, level: Column) -> Column:
        octant = F.lit(0)
        for i, d in enumerate(dims):
            octant = octant + F.shiftleft(F.call_function("shiftright", d, level).bitwiseAND(F.lit(1)), i)
        at = acc["s"] * (1 << n) + octant
        return F.struct((acc["h"] * (1 << n) + F.get(digit, at)).cast("bigint").alias("h"), F.get(follow, at).cast("int").alias("s"))

    start = F.struct(F.lit(0).cast("bigint").alias("h"), F.lit(0).alias("s"))
    return F.aggregate(F.array(*[F.lit(b) for b in range(bits - 1, -1, -1)]), start, step, lambda acc: acc["h"])


def quantised_rank(df: DataFrame, column: str, bits: int, value: str, cell: str) -> DataFrame:
    """(``value``, ``cell``) of the distinct values: their rank, spread over 2**bits cells. Written; no task sees all values."""
    values = running_total(df.select(F.col(column).alias("v")).where("v is not null").distinct().withColumn("one", F.lit(1).cast("bigint")), ["v"], "one")
    values = staged(values.select("v", "before"), "hilbert-values")
    return values.select(F.col("v").alias(value), F.expr(f"cast((before * {1 << bits}) div {max(1, values.count())} as int)").alias(cell))


def placed(docs: DataFrame, bits: int, target: int, cell: str, shard: str) -> tuple[DataFrame, int]:
    """The columns of ``docs`` with the curve's ``cell`` and the ``shard``, and the number of shards; no shuffle of the rows themselves.

    source and lang are ranked by name; the table of cells has at most 2 ** (3 * bits) rows and is broadcast, the tables of values are
    counted and broadcast only if they are small.
    """
    names = [free_name(docs, f"hb_{x}") for x in ("0", "1", "2", "hash", "v0", "v1", "size", "before")]
    d0, d1, d2, h, v0, v1, size, before = names
    top = (1 << bits) - 1
    rows = docs
    for column, value, digit in (("source", v0, d0), ("lang", v1, d1)):
        rows = rows.join(broadcast_small(quantised_rank(docs, column, bits, value, digit)), F.col(column) == F.col(value), "left")
    length = F.least(F.lit(top), F.expr(f"cast(floor(log2(1 + greatest(coalesce(n_chars, 0), 0)) * {(1 << bits) / 32}) as int)"))
    rows = rows.withColumns({d0: F.coalesce(d0, F.lit(0)), d1: F.coalesce(d1, F.lit(0)), d2: length, h: F.expr(HASH)})
    cells = rows.groupBy(d0, d1, d2).agg(F.sum(F.greatest(F.coalesce("n_chars", F.lit(0)), F.lit(0))).cast("bigint").alias(size))
    cells = cells.withColumn(cell, hilbert_index([F.col(d) for d in (d0, d1, d2)], bits))
    cells = cells.withColumn(before, F.coalesce(F.sum(size).over(Window.orderBy(cell).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    cells = staged(cells, "hilbert-cells")
    # the hash places a document uniformly inside its cell's stretch of the running total
    at = F.expr(f"cast(({before} + (cast({h} as decimal(38,0)) * {size}) div {1 << 60}) div {target} as bigint)")
    total = cells.agg(F.sum(size)).first()[0] or 0
    return rows.join(F.broadcast(cells), [d0, d1, d2]).withColumn(shard, at).select(*docs.columns, cell, shard), int(total // target) + 1


def assign(docs: DataFrame, bits: int = 5, target: int = 4_000_000) -> DataFrame:
    """(doc_id, source, lang, n_chars, cell, shard): dimensions source, language and order of magnitude of the length."""
    slim = docs.select("doc_id", "source", "lang", F.coalesce(F.col("n_chars"), F.lit(0)).cast("bigint").alias("n_chars"))
    return placed(slim, bits, target, "cell", "shard")[0]


def write(docs: DataFrame, path: str, bits: int = 5, target: int = 4_000_000) -> tuple[str, str]:
    """Write whole documents as Parquet, one file per shard, sorted by the curve; returns the names of its two columns, cell and shard.

    Texts are shuffled once, to their shards.
    """
    cell, shard = free_name(docs, "hilbert_cell"), free_name(docs, "hilbert_shard")
    out, shards = placed(docs, bits, target, cell, shard)
    out.repartitionById(shards, F.col(shard).cast("int")).sortWithinPartitions(shard, cell, "doc_id").write.parquet(path)
    return cell, shard


def extents(files: DataFrame, shard: str) -> DataFrame:
    """(shard, rows, chars, least and most of each dimension) of written shards: what the files' footers say."""
    stats = [f(c).alias(f"{n}_{c}") for c in ("source", "lang", "n_chars") for n, f in (("min", F.min), ("max", F.max))]
    return files.groupBy(F.col(shard).alias("shard")).agg(F.count("*").alias("rows"), F.sum("n_chars").alias("chars"), *stats)


def shards(docs: DataFrame, path: str, bits: int = 5, target: int = 4_000_000, lang: str = "de", chars: tuple[int, int] = (1_000, 4_000)) -> DataFrame:
    """Writes the shards and returns where each document lies with the extents of its file.

    (doc_id, source, lang, n_chars, cell, shard, min_source ... max_n_chars, skipped, skipped_share): skipped: a search for
    documents in ``lang`` with a length in the range ``chars`` needn't open this file, by its extents; skipped_share: of all files.
    """
    cell, shard = write(docs, path, bits, target)
    back = docs.sparkSession.read.parquet(path)
    per = extents(back, shard)
    # a file without a value of a dimension can't hold what is sought
    hit = (F.col("min_lang") <= lang) & (F.col("max_lang") >= lang) & (F.col("min_n_chars") <= chars[1]) & (F.col("max_n_chars") >= chars[0])
    per = staged(per.drop("rows", "chars").withColumn("skipped", ~F.coalesce(hit, F.lit(False))), "hilbert-extents")
    share = per.agg(F.round(F.avg(F.col("skipped").cast("double")), 6)).first()[0]
    rows = back.select("doc_id", "source", "lang", "n_chars", F.col(cell).alias("cell"), F.col(shard).alias("shard"))
    return rows.join(broadcast_small(per), "shard").withColumn("skipped_share", F.lit(share).cast("double"))
