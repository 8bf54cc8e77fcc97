"""Winnowed fingerprints of whole texts, in DataFrame functions alone.

A text is lower-cased and its runs of letters, marks and digits are cut into
pieces of at most 4 characters, counted from the start of each run. Each ``k``
consecutive pieces give a gram hash of 32 bits; of every ``window`` consecutive
grams the least hash is selected, of equal ones the rightmost, with its
position. Two texts that share ``window + k - 1`` consecutive pieces share a
selected hash. A text of fewer than k pieces is one gram, grams fewer than a
window are one window.

A hash and its position travel as one long, hash first and position counted
down, so that the least long is the least hash at its rightmost place.

Edge cases: null, empty and wordless texts have the empty fingerprint; two
empty fingerprints are alike (1), an empty and another one are not (0);
positions reach 2^31 - 1 pieces; repeated rows are fingerprinted each; ids are of
any type that has an order, null ids come last; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from winjoin.llm.frames import materialize

_LOW = (1 << 31) - 1
WORD = r"[\p{L}\p{M}\p{N}]{1,4}"


def _beside(a: str, step: int, f) -> Column:
    """f of each element of an array column and the one ``step`` places on, as long as there is one."""
    return F.transform(F.slice(F.col(a), F.lit(1), F.greatest(F.size(a) - step, F.lit(0))), lambda x, i: f(x, F.get(F.col(a), i + step)))


def with_fingerprint(df: DataFrame, text: str, out: str, k: int = 5, window: int = 4) -> DataFrame:
    """``df`` with a column ``out``: array<long> of selected (hash, position), in order of position.

    Hashes of 2^j pieces roll up from two of half as many, and so do least values, so a
    gram costs log2(k) steps. Each step is a column of its own, as a lambda must find its arrays ready made.
    """
    one, g = f"_{out}_1", f"_{out}_grams"
    df = df.withColumn(one, F.transform(F.regexp_extract_all(F.lower(F.coalesce(F.col(text), F.lit(""))), F.lit(WORD), F.lit(0)), lambda x: F.xxhash64(x)))
    made = {1: one}

    def step(name: str, value: Column) -> str:
        nonlocal df
        df = df.withColumn(name, value)
        return name

    size = 1
    while 2 * size <= k:
        made[2 * size] = step(f"_{out}_{2 * size}", _beside(made[size], size, lambda x, y: F.xxhash64(x, y)))
        size *= 2
    rolled, done = made[size], size
    while done < k:
        size = max(x for x in made if x <= k - done)
        other, at = made[size], done
        rolled = step(f"_{out}_roll{done + size}", F.transform(F.slice(F.col(rolled), F.lit(1), F.greatest(F.size(other) - at, F.lit(0))), lambda x, i: F.xxhash64(x, F.get(F.col(other), i + at))))
        done += size

    def packed(h: Column, at: Column) -> Column:
        return F.shiftleft(F.shiftrightunsigned(h, 32), 31).bitwiseOR(F.lit(_LOW).cast("long") - at.cast("long"))

    n = F.size(one)
    whole = F.array(packed(F.xxhash64(F.col(one)), F.lit(0)))
    df = df.withColumn(g, F.when(n == 0, F.array().cast("array<bigint>")).when(n < k, whole).otherwise(F.transform(F.col(rolled), packed)))
    least, span = g, 1
    while span < window:
        by = min(span, window - span)
        least = step(f"_{out}_least{span + by}", _beside(least, by, F.least))
        span += by
    m = F.size(g)
    df = df.withColumn(out, F.when(m == 0, F.col(g)).when(m < window, F.array(F.array_min(g))).otherwise(F.array_distinct(F.col(least))))
    return df.drop(*(c for c in df.columns if c.startswith(f"_{out}_")))


def code_point(text: Column, position: Column) -> Column:
    """Where in a text, counted in code points from 0, the piece of this number begins: shows a selected hash in its text."""
    low = F.lower(text)
    before = F.slice(F.split(low, WORD, -1), F.lit(1), position.cast("int") + 1)
    pieces = F.slice(F.regexp_extract_all(low, F.lit(WORD), F.lit(0)), F.lit(1), position.cast("int"))
    return F.char_length(F.array_join(before, "")) + F.char_length(F.array_join(pieces, ""))


def hashes(selected: Column) -> Column:
    """The distinct gram hashes of a fingerprint."""
    return F.array_distinct(F.transform(selected, lambda v: F.shiftright(v, 31)))


def as_text(selected: Column) -> Column:
    """A fingerprint as hash@position, blank-separated, hashes in hexadecimal."""
    return F.array_join(F.transform(selected, lambda v: F.concat(F.hex(F.shiftright(v, 31)), F.lit("@"), (F.lit(_LOW).cast("long") - v.bitwiseAND(F.lit(_LOW).cast("long"))).cast("string"))), " ")


def likeness(a: Column, b: Column) -> Column:
    """Jaccard similarity of two arrays of distinct hashes."""
    both = F.size(F.array_intersect(a, b))
    return F.when((F.size(a) == 0) & (F.size(b) == 0), F.lit(1.0)).otherwise(both / (F.size(a) + F.size(b) - both))


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 5, window: int = 4) -> DataFrame:
    """``docs`` (id, text) with its fingerprint: rows (doc_id, fingerprint array<long>)."""
    src = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{text_col}`").alias("_text"))
    return with_fingerprint(src, "_text", "fingerprint", k, window).select("doc_id", "fingerprint")


#: Ranges whose first rows stand in one group.
_GROUP = 4096


def with_next(docs: DataFrame, bytes_each: int = 8 << 20, least: int = 64) -> DataFrame:
    """``docs`` (doc_id of any type with an order, text) in ranges of falling doc_id, each with a copy (_ghost = 1) of the row that follows its last one.

    Rows of equal ids go by a hash of their text, equal rows by their number, so a hot id or row is cut
    like any other. A window over a range sees all its rows' successors and no window spans the table:
    first rows are found per range, handed on within groups of ranges, and from group to group by the
    first rows of these, one for each ``_GROUP`` ranges of ``bytes_each`` bytes.
    """
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    parts = max(least, int(size) // bytes_each)
    keyed = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("_tie", F.xxhash64("text")).withColumn("_number", F.monotonically_increasing_id())
    ranged = keyed.repartitionByRange(parts, F.col("doc_id").desc_nulls_last(), F.col("_tie"), F.xxhash64("_number")).drop("_number")
    # a range's number is where a task of this one shuffle stands; written, it stays what it is
    ranged = materialize(ranged.withColumn("_range", F.spark_partition_id()).withColumn("_ghost", F.lit(0)), "winnow-ranges")
    first = F.row_number().over(Window.partitionBy("_range").orderBy(F.col("doc_id").desc_nulls_last(), "_tie"))
    heads = ranged.withColumn("_k", first).where("_k = 1").drop("_k").withColumn("_group", F.floor(F.col("_range") / _GROUP).cast("int"))
    heads = heads.withColumn("_row", F.struct("doc_id", "text", "_tie"))
    inside = Window.partitionBy("_group").orderBy("_range")
    tops = heads.withColumn("_k", F.row_number().over(inside)).where("_k = 1").select(F.col("_group").alias("_g"), "_row")
    whole = Window.orderBy("_g")
    tops = tops.select("_g", F.coalesce(F.lead("_row").over(whole), F.first("_row").over(whole.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))).alias("_top"))
    ghosts = heads.withColumn("_follows", F.lead("_row").over(inside)).join(tops, F.col("_group") == F.col("_g")).withColumn("_row", F.coalesce("_follows", "_top"))
    # as many tasks as ranges: what one of them reads does not grow with the table
    return ranged.unionByName(ghosts.select("_row.doc_id", "_row.text", "_row._tie", "_range", F.lit(1).alias("_ghost"))).repartition(parts, "_range")


def _in_range() -> Window:
    return Window.partitionBy("_range").orderBy("_ghost", F.col("doc_id").desc_nulls_last(), "_tie")


def edited_likeness(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", k: int = 5, window: int = 4) -> DataFrame:
    """Each row's fingerprint beside those of an edited text and of the next row's text.

    The edited text has the last third of the code points replaced by the first
    as many of the next text. Rows (doc_id, n_chars, edited_sha256, fingerprint,
    edited_fingerprint, near_edited, near_next).
    """
    src = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{text_col}`").alias("text"))
    rows = with_next(src).withColumn("_next", F.lead("text").over(_in_range())).withColumn("n_chars", F.char_length("text").cast("long"))
    cut = F.floor(F.col("n_chars") / 3).cast("int")
    rows = rows.withColumn("_edited", F.concat(F.substring("text", F.lit(1), (F.col("n_chars") - cut).cast("int")), F.substring(F.coalesce("_next", F.lit("")), F.lit(1), cut))).drop("_next")
    rows = rows.withColumn("edited_sha256", F.sha2(F.col("_edited").cast("binary"), 256))
    rows = with_fingerprint(rows, "text", "_own", k, window).drop("text")
    rows = with_fingerprint(rows, "_edited", "_changed", k, window).drop("_edited")
    rows = rows.withColumn("_hash", hashes(F.col("_own"))).withColumn("_changed_hash", hashes(F.col("_changed")))
    rows = rows.withColumn("near_edited", likeness(F.col("_hash"), F.col("_changed_hash"))).drop("_changed_hash")
    rows = rows.withColumn("fingerprint", as_text(F.col("_own"))).withColumn("edited_fingerprint", as_text(F.col("_changed"))).drop("_own", "_changed")
    rows = rows.withColumn("_next_hash", F.lead("_hash").over(_in_range()))
    return rows.where("_ghost = 0").select("doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", likeness(F.col("_hash"), F.col("_next_hash")).alias("near_next"))
