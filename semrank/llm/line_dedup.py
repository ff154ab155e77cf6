"""Line dedup by content-defined chunks.

A text's lines with words are hashed; a rolling hash (cyclic polynomials) runs over them in a window of two lines, carried on from
window to window (blank lines between them are ignored). A boundary lies where the rolling hash turns from one that has
occurred before to one that has not, or back: it depends on the lines next to it alone, so inserted lines shift
nothing beyond their own place. What lies between boundaries, a chunk of two or more lines of which every
two neighbours stand together at an earlier place (by id, then place), is removed; the first occurrence stays.
So every run of two or more lines that occurred before goes whole, whatever surrounds it, and no single line does.

Sparser boundaries (local minima of the rolling hash) keep most passages of two and three lines, as these seldom
hold a whole chunk; that is why every line may be a boundary. The rolling hash, 128 bits made of 128 bits of each line's SHA-256, only says which
pairs of lines may have come before: the bytes of all pairs whose hash recurs are read again and compared, and unlike texts with one hash are kept apart.

At scale: hashes are rolled once and written, 16 bytes and a place per pair of lines; beside them only rows with a recurring hash move (a bitmap of
fixed size holds back most others) and the bytes of its pairs. Both aggregate partially, so a
passage that a third of all texts share costs one row per task. Pairs meet the first occurrences of repeated ones;
those that make up more than one in ``HOT`` of all repeats, fewer than ``HOT`` by arithmetic, are broadcast, the
others meet by an equi-join. Rows and the pairs that they lose meet by id.

Defined cases: null texts stay null, empty texts stay empty; rows alike in id and text are
one document and are treated alike; ids may be of any type that has an order, null ids come last when the first occurrence
is sought; what overlaps its own first occurrence (one line three times over) stays; an empty table gives an empty table; extra
columns of any name are carried.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from semrank.exec.scratch import Scratch
from semrank.llm.text import fresh, row_key

HOT = 1000
#: Windows that are rolled in one go.
PIECE = 64
#: Bits of a row key that a bitmap of rows tells apart.
MARKS = 24


def has_word(line: Column) -> Column:
    return F.length(F.translate(line, " \t\n\x0b\x0c\r", "")) > 0


def rolling(docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    """_id, _row, _k, _p: the rolling hash of the window of two lines with words, k and k + 1."""
    d = docs.select(F.col(doc_id).alias("_id"), row_key(doc_id, text).alias("_row"), F.filter(F.split(text, "\n"), has_word).alias("_full")).where(F.size("_full") > 1)
    d = d.select("_id", "_row", F.transform("_full", lambda x: F.sha2(x, 256)).alias("_h"))
    # minus as the new base: a number with a sign
    half = lambda h, at: F.conv(F.substring(h, at, 16), 16, -10).cast("bigint")
    d = d.select("_id", "_row", F.transform("_h", lambda h: F.struct(half(h, 1).alias("a"), half(h, 17).alias("b"))).alias("_h"))
    return d.select("_id", "_row", F.posexplode(rolled("_h")).alias("_k", "_p"))


def turned(x: Column, by: int) -> Column:
    """64 bits rotated to the left."""
    return F.shiftleft(x, by).bitwiseOR(F.shiftrightunsigned(x, 64 - by))


def rolled(lines: str) -> Column:
    """The hashes of all windows of two of the line hashes ``lines``, by cyclic polynomials in two lanes of 64 bits.

    The hash is carried from window to window: it is turned by a bit, the line that leaves is taken out, the one that enters is put in. As an
    array that grows is copied, each ``PIECE`` windows are rolled apart, and a piece begins with the last line of the one before.
    """
    zero = F.struct(F.lit(0).cast("bigint").alias("a"), F.lit(0).cast("bigint").alias("b"))
    start = F.struct(zero.alias("hash"), zero.alias("leaves"), zero.alias("last"), F.array().cast("array<struct<a:bigint,b:bigint>>").alias("seen"))

    def roll(state: Column, enters: Column) -> Column:
        lane = lambda c: turned(state["hash"][c], 1).bitwiseXOR(turned(state["leaves"][c], 2)).bitwiseXOR(enters[c]).alias(c)
        now = F.struct(lane("a"), lane("b"))
        return F.struct(now.alias("hash"), state["last"].alias("leaves"), enters.alias("last"), F.concat(state["seen"], F.array(now)).alias("seen"))

    def piece(at: Column) -> Column:
        # the first hash is that of one line alone
        return F.aggregate(F.slice(lines, at * PIECE + 1, F.lit(PIECE + 1)), start, roll, lambda s: F.slice(s["seen"], F.lit(2), F.lit(PIECE)))

    return F.flatten(F.transform(F.sequence(F.lit(0), F.floor((F.size(lines) - 2) / PIECE).cast("int")), piece))


def marked(rows: Column, keys: DataFrame) -> tuple[DataFrame, Column, Callable[[Column], Column]]:
    """A bitmap of ``keys``' ``_row``, 2 MB at most whatever they are: its rows, the bucket of a row key, and whether the bucket's bits may hold it."""
    low = lambda x: x.bitwiseAND(F.lit((1 << MARKS) - 1))
    bucket = F.shiftright(low(rows), 15)
    place = low(rows).bitwiseAND(F.lit(32767)).cast("int")
    at = low(F.col("_row"))
    bits = keys.groupBy(F.shiftright(at, 15).alias("_bucket")).agg(F.bitmap_construct_agg(at.bitwiseAND(F.lit(32767))).alias("_bits"))

    def held(bits: Column) -> Column:
        byte = F.conv(F.hex(F.substring(bits, F.shiftright(place, 3) + 1, F.lit(1))), 16, 10).cast("int")
        return byte.bitwiseAND(F.element_at(F.array(*[F.lit(1 << b) for b in range(8)]), place.bitwiseAND(F.lit(7)) + 1)) != 0

    return bits, bucket, held


def texts_of(docs: DataFrame, doc_id: str, text: str, asked: DataFrame) -> DataFrame:
    """_id, _row, _k, _p, _text: the bytes of the line pairs in ``asked`` (_id, _row, and _at, their numbers and hashes).

    Rows without any are left where they are, but for some that a bitmap of all row keys lets pass.
    """
    d = docs.select(F.col(doc_id).alias("_i"), row_key(doc_id, text).alias("_r"), F.col(text).alias("_t")).where("_t is not null")
    bits, bucket, held = marked(F.col("_r"), asked)
    d = d.join(F.broadcast(bits), bucket == F.col("_bucket")).where(held(F.col("_bits"))).drop("_bucket", "_bits")
    d = d.join(asked, F.col("_i").eqNullSafe(F.col("_id")) & (F.col("_r") == F.col("_row")))
    d = d.select("_id", "_row", "_at", F.filter(F.split("_t", "\n"), has_word).alias("_full"))
    d = d.select("_id", "_row", F.explode(F.transform("_at", lambda x: F.struct(x["_k"].alias("_k"), x["_p"].alias("_p"), F.concat(F.get("_full", x["_k"]), F.lit("\n"), F.get("_full", x["_k"] + 1)).alias("_text")))).alias("_x"))
    return d.select("_id", "_row", "_x.*")


def meet(pairs: DataFrame, heads: DataFrame, repeats: int, how: str = "inner") -> DataFrame:
    """``pairs`` with the row of ``heads`` of their hash; the few hot ones are broadcast."""
    hot = F.col("_n") * HOT > repeats
    few, rest = heads.where(hot).drop("_n"), heads.where(~hot).drop("_n")
    return pairs.join(F.broadcast(few), "_p", how).unionByName(pairs.join(F.broadcast(few.select("_p")), "_p", "left_anti").join(rest, "_p", how))


def removals(docs: DataFrame, doc_id: str, text: str, scratch: Scratch) -> DataFrame:
    """_id, _row and the numbers of the line pairs that go, of the rows that lose any."""
    # read three times, rolled once
    pairs = scratch.write("rolled", rolling(docs, doc_id, text))
    again = scratch.write("again", pairs.groupBy("_p").agg(F.count("*").alias("_n")).where("_n > 1"))
    repeats = again.agg(F.sum("_n")).first()[0] or 0
    asked = meet(pairs, again, repeats, "left_semi").groupBy("_id", "_row").agg(F.collect_set(F.struct("_k", "_p")).alias("_at"))
    seen = scratch.write("seen", texts_of(docs, doc_id, text, scratch.write("asked", asked)))
    place = F.struct(F.col("_id").isNull().alias("_no_id"), "_id", "_row", "_k")
    first = (F.count("*").alias("_n"), F.min(place).alias("_head"))
    # of texts that are alike, byte by byte, the least is the greatest
    heads = scratch.write("heads", seen.groupBy("_p").agg(*first, (F.min("_text") != F.max("_text")).alias("_mixed")))
    met = meet(seen.drop("_text"), heads.where("not _mixed").drop("_mixed"), repeats)
    if heads.where("_mixed").limit(1).count():
        # one hash of unlike texts: these meet by their bytes
        mixed = seen.join(heads.where("_mixed").select("_p"), "_p", "left_semi")
        met = met.unionByName(mixed.join(mixed.groupBy("_p", "_text").agg(*first), ["_p", "_text"]).drop("_n", "_text"))
    own = F.col("_id").eqNullSafe(F.col("_head._id")) & (F.col("_row") == F.col("_head._row")) & (F.col("_k") - F.col("_head._k") <= 1)
    return met.where(~own).groupBy("_id", "_row").agg(F.collect_set("_k").alias("_gone"))


def dedup_lines(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", counts: bool = False) -> DataFrame:
    """``docs`` without runs of two or more lines that occurred before; with ``counts`` also n_chunks_removed (pairs of lines) and n_lines_removed."""
    scratch = Scratch(docs.sparkSession, "lines")
    i, r, lines, full, stay, new, n_c, n_l = fresh(docs, "_did", "_drow", "_dlines", "_dfull", "_dstay", "_dnew", "n_chunks_removed", "n_lines_removed")
    gone = removals(docs, doc_id, text, scratch)
    gone = gone.select(F.col("_id").alias(i), F.col("_row").alias(r + "k"), F.col("_gone").alias(full + "g"))
    d = docs.withColumn(r, row_key(doc_id, text))
    d = d.join(gone, F.col(doc_id).eqNullSafe(F.col(i)) & (F.col(r) == F.col(r + "k")), "left")
    cut = F.col(full + "g").isNotNull()
    d = d.withColumn(lines, F.when(cut, F.split(text, "\n")))
    d = d.withColumn(full, F.filter(F.transform(lines, lambda x, k: F.when(has_word(x), k)), lambda k: k.isNotNull()))
    # from the first line of a pair to its second, with the blank lines between
    out_of = F.flatten(F.transform(full + "g", lambda k: F.sequence(F.get(full, k), F.get(full, k + 1))))
    d = d.withColumn(stay, F.when(cut, F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), out_of)))
    d = d.withColumn(new, F.when(cut, F.array_join(F.transform(stay, lambda k: F.get(lines, k)), "\n")).otherwise(F.col(text)))
    out = [F.col(new).alias(c) if c == text else F.col(c) for c in docs.columns]
    if counts:
        out += [F.when(cut, F.size(full + "g")).otherwise(0).cast("bigint").alias(n_c), F.when(cut, F.size(lines) - F.size(stay)).otherwise(0).cast("bigint").alias(n_l)]
    return d.select(*out)
