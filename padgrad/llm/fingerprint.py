"""Document fingerprints: invertible Bloom lookup sketches of paragraph digests.

A text is cut into paragraphs: at line ends and, in long lines, at sentence ends after
``SHORT`` characters (at ``LONG`` at the latest). The set of their 64-bit digests is dealt by
digest bits to 4^level buckets, so many that a bucket holds at most ``LOAD`` on average, and each bucket
goes into ``TABLES`` tables of ``WIDTH`` cells; a cell holds the count, the xor of the digests
and the xor of their checks. The fingerprint is the number of digests and all cells. Four buckets that
differ in their last digit add up to one bucket of the level below, so a fingerprint holds every smaller
sketch of its text too.

The difference of two sketches holds only what one of the texts has and the other has not; cells with one
digest are peeled until none is left, which gives the differing digests. The smallest sketch is tried
first; on failure one as large as the larger fingerprint is peeled, bucket by bucket (the other text's digests,
which its own sketch gives when it is peeled, are dealt to as many buckets). What even that leaves is counted from below: a cell with n more digests of one text holds at least |n|, at least 2
if n is 0, at least 3 if |n| is 1 but it is not one digest.

Likeness is shared over united digests, from the two set sizes and the difference: two fingerprints
give it, without the texts (``likeness`` for columns, ``likeness_of`` for two stored strings). All of it is
higher-order functions on arrays in one row: no shuffle, and work in proportion to the text's length.

Defined cases: null and empty texts have an empty sketch, and two of them have
likeness 1; repeated paragraphs count once; equal texts have equal fingerprints; a text of more than
``LOAD * 4^LEVELS`` paragraphs has fuller buckets; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from padgrad.llm.textcols import NO_ID, id_key
from padgrad.shared import written

TABLES, WIDTH, BITS, ROUNDS = 3, 8, 3, 8
#: Digests a bucket holds on average at most, and levels of buckets (each takes two bits of the digests).
LOAD, LEVELS = 4, 8
#: Ids with more than 1/HOT_IDS of all rows are dealt to SALTS tasks.
HOT_IDS, SALTS = 1000, 64
SHORT, LONG = 48, 200
_PARAGRAPH = rf"(?s)(?:.{{{SHORT},{LONG}}}?(?:(?<=[.!?])\s+|\n+|\z)|.{{1,{LONG}}})"


def _shift(x: Column, by: Column) -> Column:
    return F.call_function("shiftrightunsigned", x, by)


def paragraph_digests(text: Column) -> Column:
    """Distinct 64-bit digests of a text's paragraphs."""
    parts = F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(_PARAGRAPH), F.lit(0))
    return F.array_distinct(F.transform(F.filter(parts, lambda p: p != ""), lambda p: F.xxhash64(p)))


def _check(digest: Column) -> Column:
    return F.xxhash64(digest, F.lit(97)).bitwiseAND(F.lit(0xFFFFFFFF))


def _cell(n: Column, k: Column, c: Column) -> Column:
    return F.struct(n.cast("int").alias("n"), k.alias("k"), c.alias("c"))


def items(digests: Column) -> Column:
    """Digests with all that the sketches ask of them: check and the place of their cell in each table."""

    def one(d):
        places = [(_shift(d, F.lit(t * BITS)).bitwiseAND(F.lit(WIDTH - 1)).cast("int") + t * WIDTH).alias(f"p{t}") for t in range(TABLES)]
        return F.struct(d.alias("k"), _check(d).alias("c"), *places)

    return F.transform(digests, one)


def sketch(elements: Column) -> Column:
    """The cells of a set of ``items``: ``array<struct<n, k, c>>``."""
    zero = _cell(F.lit(0), F.lit(0).cast("long"), F.lit(0).cast("long"))

    def table(t):
        def cell(place):
            own = F.filter(elements, lambda x: x[f"p{t}"] == place)
            return F.aggregate(own, zero, lambda a, x: _cell(a["n"] + 1, a["k"].bitwiseXOR(x["k"]), a["c"].bitwiseXOR(x["c"])))

        return F.transform(F.sequence(F.lit(t * WIDTH), F.lit((t + 1) * WIDTH - 1)), cell)

    return F.concat(*[table(t) for t in range(TABLES)])


def subtract(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: _cell(x["n"] - y["n"], x["k"].bitwiseXOR(y["k"]), x["c"].bitwiseXOR(y["c"])))


def _left(cells: Column) -> Column:
    return F.exists(cells, lambda c: (c["n"] != 0) | (c["k"] != 0))


def peel(cells: Column) -> Column:
    """``struct(cells, count)``: what is left, and how many digests were peeled, of either text."""
    start = F.struct(cells.alias("cells"), F.lit(0).alias("count"))

    def turn(state, _):
        pure = F.filter(state["cells"], lambda c: (F.abs(c["n"]) == 1) & (_check(c["k"]) == c["c"]))
        distinct = F.array_distinct(F.transform(pure, lambda c: F.struct(c["k"].alias("k"), c["n"].alias("n"))))
        found = F.zip_with(distinct, items(F.transform(distinct, lambda x: x["k"])), lambda x, y: F.struct(x["n"].alias("n"), y["k"].alias("k"), y["c"].alias("c"), y["p0"].alias("p0"), y["p1"].alias("p1"), y["p2"].alias("p2")))

        def without(pieces):
            def cleared(c, place):
                own = F.filter(pieces, lambda t: (t["p0"] == place) | (t["p1"] == place) | (t["p2"] == place))
                return F.aggregate(own, c, lambda a, t: _cell(a["n"] - t["n"], a["k"].bitwiseXOR(t["k"]), a["c"].bitwiseXOR(t["c"])))

            return F.struct(F.transform(state["cells"], cleared).alias("cells"), (state["count"] + F.size(pieces)).alias("count"))

        # the found pieces are made once for the turn: as the one element of an array
        after = F.get(F.transform(F.array(found), without), F.lit(0))
        stop = ~_left(state["cells"])  # nothing to peel any more
        return F.when(stop, state).otherwise(after)

    return F.aggregate(F.sequence(F.lit(1), F.lit(ROUNDS)), start, turn)


def level_of(n: Column) -> Column:
    """Levels of a set of ``n`` digests."""
    return F.least(F.lit(LEVELS), F.greatest(F.lit(0), F.ceil(F.log(n.cast("double") / LOAD) / F.log(F.lit(4.0))))).cast("int")


def _steps(n: Column) -> Column:
    return F.when(n > 0, F.sequence(F.lit(0), n - 1)).otherwise(F.array().cast("array<int>"))


def sketches(digests: Column, level: Column) -> Column:
    """The sketch of a set of digests at ``level``: ``array<array<cell>>``, a bucket each."""

    def deal(parts, step):
        at = F.lit(TABLES * BITS) + 2 * step

        def four(part):
            return F.transform(F.sequence(F.lit(0), F.lit(3)), lambda b: F.filter(part, lambda x: _shift(x["k"], at).bitwiseAND(F.lit(3)) == b))

        return F.flatten(F.transform(parts, four))

    return F.transform(F.aggregate(_steps(level), F.array(items(digests)), deal), sketch)


def whole_sketch(digests: Column) -> Column:
    """``struct<d, n, level, s>``: digests, their number, level and sketch; all but ``d`` is the fingerprint."""

    def one(d):
        level = level_of(F.size(d))
        return F.struct(d.alias("d"), F.size(d).alias("n"), level.alias("level"), sketches(d, level).alias("s"))

    return F.get(F.transform(F.array(digests), one), F.lit(0))


def _added(a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda x, y: _cell(x["n"] + y["n"], x["k"].bitwiseXOR(y["k"]), x["c"].bitwiseXOR(y["c"])))


def folded(buckets: Column, times: Column) -> Column:
    """The sketch ``times`` levels below."""

    def fold(acc, _):
        return F.transform(F.sequence(F.lit(0), (F.size(acc) / 4).cast("int") - 1), lambda i: _added(_added(F.get(acc, 4 * i), F.get(acc, 4 * i + 1)), _added(F.get(acc, 4 * i + 2), F.get(acc, 4 * i + 3))))

    return F.aggregate(_steps(times), buckets, fold)


def _least_left(cells: Column) -> Column:
    """At least so many digests are in cells that were not peeled: the most that one table shows."""

    def shown(c):
        n = F.abs(c["n"])
        return F.when((n == 0) & (c["k"] != 0), F.lit(2)).when((n == 1) & (_check(c["k"]) != c["c"]), F.lit(3)).otherwise(n)

    tables = [F.aggregate(F.slice(cells, t * WIDTH + 1, WIDTH), F.lit(0), lambda acc, c: acc + shown(c)) for t in range(TABLES)]
    return F.greatest(*tables)


def _peeled(cells: Column) -> Column:
    """``struct(count, left)`` of a bucket of differences; most buckets of like texts hold none."""
    none = F.struct(F.lit(0).alias("count"), F.lit(0).alias("left"))
    done = F.get(F.transform(F.array(peel(cells)), lambda s: F.struct(s["count"].alias("count"), F.when(_left(s["cells"]), _least_left(s["cells"])).otherwise(F.lit(0)).alias("left"))), F.lit(0))
    return F.when(_left(cells), done).otherwise(none)


def difference_size(a: Column, b: Column) -> Column:
    """Size of the symmetric difference of two sets, from their ``whole_sketch``."""

    def of(p):
        level = F.greatest(p["a"]["level"], p["b"]["level"])
        a_, b_ = (F.when(p[x]["level"] == level, p[x]["s"]).otherwise(sketches(p[x]["d"], level)) for x in "ab")
        cells = F.zip_with(a_, b_, lambda x, y: subtract(x, y))

        def tried(q):
            # differences that plainly do not fit the smallest sketch are not tried there
            least = F.get(folded(q["cells"], q["level"]), F.lit(0))
            many = F.struct(F.lit(0).alias("count"), F.lit(1).alias("left"))
            small = F.get(F.transform(F.array(least), lambda c: F.when((q["level"] > 0) & (_least_left(c) > TABLES * WIDTH // 2), many).otherwise(_peeled(c))), F.lit(0))
            whole = F.aggregate(F.transform(q["cells"], _peeled), F.lit(0), lambda acc, x: acc + x["count"] + x["left"])
            return F.get(F.transform(F.array(small), lambda s: F.when((s["left"] == 0) | (q["level"] == 0), s["count"] + s["left"]).otherwise(whole)), F.lit(0))

        return F.get(F.transform(F.array(F.struct(cells.alias("cells"), level.alias("level"))), tried), F.lit(0))

    return F.get(F.transform(F.array(F.struct(a.alias("a"), b.alias("b"))), of), F.lit(0))


def likeness(n_a: Column, n_b: Column, difference: Column) -> Column:
    """Shared over united digests, from set sizes and the size of the difference."""
    shared = (n_a + n_b - difference) / 2
    return F.when(n_a + n_b > 0, shared / (n_a + n_b - shared)).otherwise(F.lit(1.0))


def fingerprint_text(whole: Column) -> Column:
    """The fingerprint as a string, base64 of: digests (4 bytes), levels (1), then each cell that is not empty: its number (4), count (2), xor of digests (8) and of checks (4)."""

    def one(c, at):
        cell = F.concat(F.lpad(F.hex(at.cast("long")), 8, "0"), F.right(F.lpad(F.hex(c["n"].cast("long")), 4, "0"), F.lit(4)), F.lpad(F.hex(c["k"]), 16, "0"), F.lpad(F.hex(c["c"]), 8, "0"))
        return F.when((c["n"] != 0) | (c["k"] != 0), cell).otherwise(F.lit(""))

    head = F.concat(F.lpad(F.hex(whole["n"].cast("long")), 8, "0"), F.lpad(F.hex(whole["level"].cast("long")), 2, "0"))
    return F.base64(F.unhex(F.concat(head, F.array_join(F.transform(F.flatten(whole["s"]), one), ""))))


def _long_check(k: int) -> int:
    """``_check`` of an unsigned digest in plain Python."""
    import xxhash

    return xxhash.xxh64_intdigest((97).to_bytes(4, "little"), xxhash.xxh64_intdigest(k.to_bytes(8, "little"), 42)) & 0xFFFFFFFF


def likeness_of(a: str, b: str) -> float:
    """Likeness of two stored fingerprints, for a user who holds no more than the strings (plain Python; ``likeness`` is the one for tables)."""
    import base64
    import struct

    def read(text):
        raw = base64.b64decode(text)
        n, level = struct.unpack_from(">IB", raw)
        return n, level, {at: [x, k, c] for at, x, k, c in struct.iter_unpack(">IhQI", raw[5:])}

    size = TABLES * WIDTH

    def cells_of(k, x=1):
        return [((k >> (t * BITS) & (WIDTH - 1)) + t * WIDTH, (x, k, _long_check(k))) for t in range(TABLES)]

    def put(cell, piece, sign=1):
        cell[0], cell[1], cell[2] = cell[0] + sign * piece[0], cell[1] ^ piece[1], cell[2] ^ piece[2]

    def buckets(sets, level):
        """Differences of ``(cells, own level, sign)`` by bucket."""
        out: dict[int, list] = {}
        for cells, own, sign in sets:
            for at, piece in cells.items():
                put(out.setdefault((at // size) >> (2 * (own - level)), [[0, 0, 0] for _ in range(size)])[at % size], piece, sign)
        return out

    def count(sets, level):
        return sum(len(found) + left for found, left in map(peeled, buckets(sets, level).values()))

    def least_left(cells):
        shown = [2 if not x and k else 3 if abs(x) == 1 and _long_check(k) != c else abs(x) for x, k, c in cells]
        return max(sum(shown[t * WIDTH : (t + 1) * WIDTH]) for t in range(TABLES))

    def peeled(cells):
        """Digests found, and how many more there are at least."""
        found = []
        for _ in range(ROUNDS):
            pure = {(k, x) for x, k, c in cells if abs(x) == 1 and _long_check(k) == c}
            for k, x in pure:
                for at, piece in cells_of(k, x):
                    put(cells[at], piece, -1)
            found += [k for k, _ in pure]
        return found, least_left(cells)

    (n_a, la, a_), (n_b, lb, b_) = read(a), read(b)
    sets = sorted([(a_, la, 1), (b_, lb, -1)], key=lambda x: x[1])
    (less, low, sign), (more, high, other) = sets
    least = next(iter(buckets(sets, 0).values()), [[0, 0, 0]] * size)
    plain = None if high and least_left(least) > size // 2 else peeled(least)
    if plain and (not high or not plain[1]):
        difference = len(plain[0]) + plain[1]
    elif low == high:
        difference = count(sets, high)
    else:  # the smaller text's digests are dealt to as many buckets; of a bucket where some do not peel out, the difference at its own level is tried first
        raised: dict[int, list] = {}
        difference, settled, coarse = 0, set(), buckets(sets, low)
        for k, cells in buckets([(less, low, 1)], low).items():
            found, left = peeled(cells)
            if left:
                own, more_left = peeled(coarse[k])
                if not more_left:
                    difference += len(own)
                    settled.add(k)
                    continue
            difference += left
            for digest in found:
                bucket = 0
                for step in range(high):
                    bucket = 4 * bucket + (digest >> (TABLES * BITS + 2 * step) & 3)
                for at, piece in cells_of(digest):
                    put(raised.setdefault(bucket * size + at, [0, 0, 0]), piece)
        rest = {at: piece for at, piece in more.items() if (at // size) >> (2 * (high - low)) not in settled}
        difference += count([(raised, high, sign), (rest, high, other)], high)
    shared = (n_a + n_b - difference) / 2
    return shared / (n_a + n_b - shared) if n_a + n_b else 1.0


def successors(ids: DataFrame) -> DataFrame:
    """``(did, user, user_chars)``: the document that has ``did`` as its next one in descending order, and its size.

    The largest id comes after the smallest. Only narrow rows are ranged and shuffled.
    """
    t = written(ids.repartitionByRange(F.col("did").desc()).select("did", "n", F.spark_partition_id().alias("part")), "fp-order")
    w = Window.partitionBy("part").orderBy(F.col("did").desc())
    inner = t.select("did", "part", F.lag("did").over(w).alias("user"), F.lag("n").over(w).alias("user_chars"))
    ends = t.groupBy("part").agg(F.min(F.struct("did", "n")).alias("last"))
    by = Window.partitionBy().orderBy("part")  # a row for each range
    over = F.max("part").over(Window.partitionBy())
    ends = ends.select("part", F.lag("last").over(by).alias("before"), F.max(F.when(F.col("part") == over, F.col("last"))).over(Window.partitionBy()).alias("wrap"))
    edge = F.coalesce("before", "wrap")
    joined = inner.join(F.broadcast(ends), "part")
    none = F.col("user_chars").isNull()
    return joined.select("did", F.when(none, edge["did"]).otherwise(F.col("user")).alias("user"), F.when(none, edge["n"]).otherwise(F.col("user_chars")).alias("user_chars"))


def _heads(rows: DataFrame, order: DataFrame) -> DataFrame:
    """``(did, head, next_dig)``: what the document before takes of each of ``rows``."""
    return rows.join(order.hint("merge"), "did").select(F.col("user").alias("did"), F.expr("substring(text, 1, int(user_chars div 2))").alias("head"), F.col("dig").alias("next_dig"))


def fingerprint_edits(docs: DataFrame) -> DataFrame:
    """Fingerprints of every text and of its edited text, and how alike they are.

    The edited text ends with the beginning of the next document (descending ids, the
    first after the last) in place of its second half. Rows with one id: each has its
    own row; as a next document the least text of them stands. A null id is the least.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    base = docs.select(id_key(F.col("doc_id")).alias("did"), text.alias("text"))
    sizes = base.select("did", F.char_length("text").alias("n"))
    ids = written(sizes.groupBy("did").agg(F.max("n").alias("n"), F.count("*").alias("copies")), "fp-ids")
    repeated = not ids.where("copies > 1").isEmpty()
    order = successors(ids.select("did", "n"))
    rich = base.withColumn("dig", paragraph_digests(F.col("text")))
    part = ["did"]
    if not repeated:
        rich = rich.repartition("did")
        heads = _heads(rich, order)
    else:  # rows of a frequent id are spread over SALTS tasks, each with a copy of the next document's head
        least = rich.groupBy("did").agg(F.min(F.struct("text", "dig")).alias("x")).select("did", "x.text", "x.dig")
        cut = max(SALTS, ids.agg(F.sum("copies")).first()[0] // HOT_IDS)
        hot = F.broadcast(ids.where(F.col("copies") > cut).select("did", F.lit(SALTS).alias("salts")))  # at most HOT_IDS rows
        part = ["did", "salt"]
        salt = F.pmod(F.monotonically_increasing_id(), F.coalesce("salts", F.lit(1)))
        rich = written(rich.join(hot, "did", "left").withColumn("salt", salt).drop("salts"), "fp-salted")  # written, so a task that is run again finds the same salts
        heads = _heads(least, order).join(hot, "did", "left").withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("salts", F.lit(1)).cast("long") - 1))).drop("salts")
    both = rich.join(heads.hint("merge"), part)
    n = F.char_length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.expr("substring(text, 1, int(char_length(text) - char_length(text) div 2))"), F.substring(F.col("head"), F.lit(1), half))
    made = both.select("did", n.cast("long").alias("n_chars"), edited.alias("edited"), "dig", "next_dig")
    made = made.select("did", "n_chars", F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"), "dig", "next_dig", paragraph_digests(F.col("edited")).alias("edit_dig"))
    made = made.select("did", "n_chars", "edited_sha256", *[whole_sketch(F.col(c)).alias(name) for c, name in (("dig", "own"), ("edit_dig", "edit"), ("next_dig", "next"))])
    made = made.withColumn("d_edit", difference_size(F.col("own"), F.col("edit"))).withColumn("d_next", difference_size(F.col("own"), F.col("next")))
    return made.select(
        F.when(F.col("did") != NO_ID, F.col("did")).alias("doc_id"), "n_chars", "edited_sha256",
        fingerprint_text(F.col("own")).alias("fingerprint"), fingerprint_text(F.col("edit")).alias("edited_fingerprint"),
        likeness(F.col("own.n"), F.col("edit.n"), F.col("d_edit")).alias("near_edited"), likeness(F.col("own.n"), F.col("next.n"), F.col("d_next")).alias("near_next"),
    )
