"""Document fingerprints as invertible Bloom lookup sketches, in DataFrame functions alone.

A text's units are its paragraphs, long paragraphs cut at sentence ends; each distinct unit is a 64-bit digest. A
sketch has three subtables; a digest goes to one cell of each, and a cell holds a count, the xor of its digests and
the xor of their check hashes. Two versions' sketches subtract cell by cell, and peeling cells that hold one
digest recovers the digests on either side. A sketch that does not peel fails visibly, in cells left over; the pair is
then retried with twice the cells, and again until it peels.

Over a whole table this is done in generated code: a document's digests become rows of cells, an aggregation by cell
builds the difference of both sketches, and each round of peeling is one more aggregation. A round looks at one
subtable only, where a digest has one cell, so that no digest is taken out twice.

Texts cross the network once, to find each document's successor in descending id order; documents at the edge of
an id range are copied into the range above, which makes that window local. What leaves this stage, through a table in
the shared folder, is digests and no text. They are dealt once more by row, in as many partitions as their cells
need, and all rounds run inside these partitions.

``fingerprint`` is the smallest sketch (``BASE`` cells), equal for equal texts. The likeness of two texts is the share of
their units that no peeled difference holds: 1 - |difference| / (units of both).

Defined cases: null text is the empty text, which has no units; two texts without units are alike (1), one
without is unlike the other (0); repeated ids are ordered by text; a null id comes after all others; the last
document is followed by the first, a single one by itself; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from evalengine.llm._common import checkpointed, table, whole_text

UNIT_END = r"\n+|(?<=[.!?])\s+"
BASE, ROUNDS, ROOM = 24, 18, 0.55
CELLS_A_TASK = 6_000_000
KEYS = ("row", "pair", "third", "cell")


def units(text: Column) -> Column:
    """Digests of a text's distinct units."""
    return F.array_distinct(F.transform(F.filter(F.split(text, UNIT_END), lambda u: F.length(u) > 0), lambda u: F.xxhash64(u)))


def _check(key: Column) -> Column:
    return F.xxhash64(key, F.lit("check"))


def _slot(key: Column, j: int, third: Column) -> Column:
    """A digest's cell in subtable j: 21 of its bits, spread."""
    return F.pmod(F.call_function("shiftrightunsigned", key, F.lit(j * 21)).bitwiseAND(F.lit(0x1FFFFF)) * 2654435761, third).cast("int") + third * j


def _summed(rows: DataFrame) -> DataFrame:
    """Sum what falls into each cell; cells that are empty go."""
    return rows.groupBy(*KEYS).agg(F.sum("c").alias("c"), F.bit_xor("k").alias("k"), F.bit_xor("h").alias("h")).where("cell < 0 OR c <> 0 OR k <> 0 OR h <> 0")


def sketched(listed: DataFrame, parts: list[tuple[str, int, int, Column]]) -> DataFrame:
    """Cells of the sums of the lists' sketches. A part: a column of digests, its pair, its sign, the cells of a subtable."""

    def placed(digests: str, pair: int, sign: int, wide: Column) -> Column:
        return F.transform(digests, lambda d: F.struct(F.lit(pair).alias("pair"), wide.cast("int").alias("third"), F.lit(sign).cast("long").alias("c"), d.alias("k")))

    items = F.concat(*(placed(*part) for part in parts))
    rows = listed.select("row", F.explode(items).alias("x")).select("row", "x.pair", "x.third", "x.c", "x.k").withColumn("h", _check(F.col("k")))
    return _summed(rows.withColumn("cell", F.explode(F.array(*(_slot(F.col("k"), j, F.col("third")) for j in range(3))))))


def peeled(cells: DataFrame) -> DataFrame:
    """Peel difference sketches. Digests found count in the cells -1 (only in the first text) and -2 (only in the second)."""
    none = F.lit(0).cast("long")
    row = lambda cell, c, k, h: F.struct(cell.cast("int").alias("cell"), c.cast("long").alias("c"), k.alias("k"), h.alias("h"))
    for r in range(ROUNDS):
        j, third = r % 3, F.col("third")
        pure = (F.abs("c") == 1) & (F.col("cell") >= third * j) & (F.col("cell") < third * (j + 1)) & (F.col("h") == _check(F.col("k")))
        others = [row(_slot(F.col("k"), i, third), -F.col("c"), F.col("k"), F.col("h")) for i in range(3) if i != j]
        found = row(F.when(F.col("c") > 0, -1).otherwise(-2), F.lit(1), none, none)
        kept = row(F.col("cell"), F.col("c"), F.col("k"), F.col("h"))
        moved = cells.withColumn("x", F.explode(F.when(pure, F.array(*others, found)).otherwise(F.array(kept))))
        cells = _summed(moved.select("row", "pair", "third", "x.cell", "x.c", "x.k", "x.h"))
    return cells


def written(cells: Column) -> Column:
    """A sketch's cells in use as text: index, count, key and check, in base 64."""
    spelled = F.array_join(F.transform(cells, lambda c: F.concat(F.lpad(F.hex(c["cell"]), 2, "0"), F.lpad(F.hex(F.pmod(c["c"], F.lit(65536))), 4, "0"), F.lpad(F.hex(c["k"]), 16, "0"), F.lpad(F.hex(c["h"]), 16, "0"))), "")
    return F.base64(F.unhex(spelled))


def differences(listed: DataFrame, room: float, parts: int) -> DataFrame:
    """For each row: how many digests are only in the text (``gone``), only in the other (``new``), and the cells left over,
    for the edited text (0) and the next document (1), by sketches with ``room`` cells a digest in each subtable."""
    wide = lambda x, y: F.ceil((F.size(x) + F.size(y)) * room) + 11
    dealt = listed.repartition(parts, "row")
    cells = peeled(sketched(dealt, [("a", 0, 1, wide("a", "e")), ("e", 0, -1, wide("a", "e")), ("a", 1, 1, wide("a", "n")), ("n", 1, -1, wide("a", "n"))]))
    count = lambda pair, cell: F.coalesce(F.sum(F.when((F.col("pair") == pair) & (F.col("cell") == cell), F.col("c"))), F.lit(0))
    return cells.groupBy("row").agg(*(f.alias(f"{name}{p}") for p in (0, 1) for name, f in (("gone", count(p, -1)), ("new", count(p, -2)))), F.count_if(F.col("cell") >= 0).alias("left"))


def settled(listed: DataFrame, parts: int) -> DataFrame:
    """``differences`` of all rows, retried with twice the room as long as any sketch does not peel; rows without digests are left out."""
    room, rest, done = ROOM, listed, None
    while True:
        found = checkpointed(differences(rest, room, parts))
        good = found.where("left = 0")
        done = good if done is None else done.unionAll(good)
        again = found.where("left > 0").select("row")
        n = again.count()
        if not n:
            return done
        room, rest, parts = 2 * room, listed.join(again, "row", "left_semi"), max(1, min(parts, n))


def _above(bounds: Column, n: int, value: Column) -> Column:
    """How many of ``n`` sorted bounds lie below a value, by halving."""
    start = F.struct(F.lit(0).alias("lo"), F.lit(n).alias("hi"))

    def step(s: Column, _: Column) -> Column:
        mid = F.floor((s["lo"] + s["hi"]) / 2).cast("int")
        less = F.get(bounds, mid) < value
        return F.when(s["lo"] >= s["hi"], s).otherwise(F.struct(F.when(less, mid + 1).otherwise(s["lo"]).alias("lo"), F.when(less, s["hi"]).otherwise(mid).alias("hi")))

    return F.aggregate(F.sequence(F.lit(1), F.lit(n.bit_length())), start, step, lambda s: s["lo"])


def followed(docs: DataFrame, ranges: int | None = None) -> DataFrame:
    """``docs`` (doc_id, text, ...) with ``next_text``, the text of the next document in descending id
    order, and ``row``, a number of its own for each row."""
    spark = docs.sparkSession
    ranges = ranges or 4 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    keyed = docs.withColumn("at", F.coalesce("doc_id", F.lit(-(1 << 63) + 1)))
    steps = [i / ranges for i in range(1, ranges)]
    about = sorted(set(keyed.agg(F.percentile_approx("at", [*steps, 1.0], 100 * ranges)).first()[0] or []))
    literal = lambda values: F.from_json(F.lit(json.dumps(values)), "array<bigint>")
    # Percentiles pass through doubles; the largest id of each range is the bound that is exact.
    bounds = sorted(r[0] for r in keyed.groupBy(_above(literal(about), len(about), F.col("at"))).agg(F.max("at").alias("at")).select("at").collect()) if about else []
    if not bounds:
        return docs.withColumns({"next_text": F.lit(None).cast("string"), "row": F.lit(0).cast("long")})
    edge = literal(bounds)
    own = _above(edge, len(bounds), F.col("at"))
    ends = F.get(edge, F.col("own")) == F.col("at")
    above = F.when(F.col("at") == bounds[-1], F.struct(F.lit(0).alias("range"), F.lit(2).alias("rank"))).when(ends, F.struct((F.col("own") + 1).alias("range"), F.lit(1).alias("rank")))
    placed = keyed.withColumn("own", own).withColumn("place", F.explode(F.array_compact(F.array(F.struct(F.col("own").alias("range"), F.lit(0).alias("rank")), above)))).select("doc_id", "text", "at", "place.range", "place.rank")
    order = Window.partitionBy("range").orderBy("rank", F.desc("at"), F.desc("text"))
    numbered = placed.withColumns({"next_text": F.lead("text").over(order), "number": F.row_number().over(order)})
    return numbered.where("rank = 0").withColumn("row", F.col("range").cast("long") * (1 << 40) + F.col("number")).drop("at", "range", "rank", "number")


def fingerprints(docs: DataFrame) -> DataFrame:
    """Fingerprints of each text and of its edited form, and their likenesses; see the module for the cases."""
    read = followed(docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text")))
    sized = read.withColumn("n_chars", F.length("text").cast("long")).withColumn("cut", F.floor(F.col("n_chars") / 2).cast("int"))
    edited = sized.withColumn("edited", F.concat(F.substring("text", F.lit(1), (F.col("n_chars") - F.col("cut")).cast("int")), F.substring("next_text", F.lit(1), F.col("cut"))))
    listed = checkpointed(edited.select("row", "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), units(F.col("text")).alias("a"), units(F.col("edited")).alias("e"), units(F.col("next_text")).alias("n")))
    sizes = lambda *lists: sum((F.size(x).cast("long") for x in lists), F.lit(0))
    cells = listed.agg(F.sum(3 * sizes("a", "a", "e", "n"))).first()[0] or 0
    parts = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-cells // CELLS_A_TASK))
    found = settled(listed.select("row", "a", "e", "n"), parts)
    third = F.lit(BASE // 3)
    base = sketched(listed.select("row", "a", "e").repartition(parts, "row"), [("a", 0, 1, third), ("e", 1, 1, third)])
    held = lambda pair: F.sort_array(F.collect_list(F.when(F.col("pair") == pair, F.struct("cell", "c", "k", "h"))))
    prints = base.groupBy("row").agg(written(held(0)).alias("fingerprint"), written(held(1)).alias("edited_fingerprint"))
    rows = listed.select("row", "doc_id", "n_chars", "edited_sha256", *(F.size(x).cast("long").alias(f"n_{x}") for x in "aen"))
    both = rows.join(prints, "row", "left").join(found, "row", "left")
    near = lambda other, p: F.when(F.col("n_a") + F.col(other) == 0, 1.0).otherwise(1 - (F.coalesce(f"gone{p}", F.lit(0)) + F.coalesce(f"new{p}", F.lit(0))) / (F.col("n_a") + F.col(other)))
    return both.select(
        "doc_id", "n_chars", "edited_sha256", F.coalesce("fingerprint", F.lit("")).alias("fingerprint"), F.coalesce("edited_fingerprint", F.lit("")).alias("edited_fingerprint"),
        near("n_e", 0).alias("near_edited"), near("n_n", 1).alias("near_next"), F.col("n_a").alias("n_units"), F.coalesce("gone0", F.lit(0)).alias("gone"), F.coalesce("new0", F.lit(0)).alias("new"),
    )


def op7_iblt_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints(table(spark, sf_dir, "documents"))
