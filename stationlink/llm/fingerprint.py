"""Document fingerprints by a homomorphic multiset hash, in DataFrame functions only.

Each paragraph (a line that isn't blank) is hashed to a wide vector; a text's vector is their sum, lane by lane, modulo
2^32. So the order of paragraphs does not matter, and paragraphs are added or taken away without the rest of the text.
A second vector is made of smaller pieces, parts of a line up to a mark such as a full stop, so that an edit changes the
pieces around it only: each piece adds a bit, drawn from its hash, to each of ``LANES`` lanes modulo 2^16. Twice a lane less the number of pieces is a sum of random signs, one a piece; such sums keep distances
of multisets, whatever the length of the texts, and tell how like two texts are. Texts of at most ``SHORT`` characters,
which have few such pieces, have a third vector of the same kind over all runs of three characters.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

WIDE, LANES, SHORT_LANES = 16, 128, 64
#: Most characters of a text whose runs of three characters count.
SHORT = 400
#: Pieces end after these; longer ones than the first number are cut into parts of the second one.
MARKS, LONG, PART = (". ", ", ", "! ", "? ", "; ", "| ", "。", "，"), 160, 64
ROWS_PER_RANGE, MAX_RANGES_SQRT = 1000, 128
_M32 = (1 << 32) - 1
#: Eight lanes of 8 bits in a long: their lowest bits, and every second of them; every second of four lanes of 16 bits.
_ONES, _BYTES, _EVEN = 0x0101010101010101, 0x00FF00FF00FF00FF, 0x0000FFFF0000FFFF
#: So many pieces are summed in lanes of 8 bits at once, as none then runs over into the next one.
_AT_ONCE = 127

# Expressions are written in SQL, as one text each: built call by call, they would take the driver seconds.


def _bound(value: str, name: str, use: str) -> str:
    """``use``, in which ``name`` stands for ``value``, made once."""
    return f"transform(array({value}), {name} -> {use})[0]"


def _wide(text: str) -> str:
    lane = "aggregate(digests, 0L, (s, d) -> s + (xxhash64({k}, d) & {m}), s -> s & {m})"
    found = f"transform(filter(split(coalesce({text}, ''), '\n'), p -> trim(p) != ''), p -> sha2(p, 256))"
    return _bound(found, "digests", "array(" + ", ".join(lane.format(k=k, m=f"{_M32}L") for k in range(WIDE)) + ")")


def wide_lanes(text: str) -> Column:
    """array<bigint> of WIDE sums modulo 2^32 over the paragraphs of ``text`` (SQL); zeros for null or blank texts."""
    return F.expr(_wide(text))


def added(a: str, b: str) -> Column:
    """Wide lanes of two texts' paragraphs together."""
    return F.expr(f"zip_with({a}, {b}, (x, y) -> (x + y) & {_M32}L)")


def removed(a: str, b: str) -> Column:
    """Wide lanes of ``a`` without the paragraphs behind ``b``."""
    return F.expr(f"zip_with({a}, {b}, (x, y) -> (x - y) & {_M32}L)")


def _plus(a: str, b: str) -> str:
    """Sums modulo 2^16 of the four lanes of two longs."""
    low, high = f"((({a} & {_EVEN}L) + ({b} & {_EVEN}L)) & {_EVEN}L)", f"(((shiftrightunsigned({a}, 16) & {_EVEN}L) + (shiftrightunsigned({b}, 16) & {_EVEN}L)) & {_EVEN}L)"
    return f"({low} | shiftleft({high}, 16))"


def _packed(hashes: str, lanes: int) -> str:
    """Lanes of an array of hashes, four in a long: bit j of each byte of a hash goes to lanes of the j-th pair of longs."""

    def sums(of: str) -> str:
        one = "array(" + ", ".join(f"aggregate({{of}}, 0L, (s, h) -> s + (shiftrightunsigned(h, {j}) & {_ONES}L))" for j in range(8)) + ")"
        rest = [_bound(f"transform({of}, h -> xxhash64(h, {k}))", "again", one.format(of="again")) for k in range(1, lanes // 64)]
        return f"flatten(transform(concat({', '.join([one.format(of=of), *rest])}), x -> array(x & {_BYTES}L, shiftrightunsigned(x, 8) & {_BYTES}L)))"

    part = _bound(f"slice(hashes, cast(k * {_AT_ONCE} + 1 as int), {_AT_ONCE})", "part", sums("part"))
    parts = f"transform(sequence(0, cast(floor((size(hashes) - 1) / {_AT_ONCE}) as int)), k -> {part})"
    whole = f"aggregate({parts}, array_repeat(0L, {lanes // 4}), (t, x) -> zip_with(t, x, (p, q) -> {_plus('p', 'q')}))"
    return _bound(hashes, "hashes", f"if(size(hashes) <= {_AT_ONCE}, {sums('hashes')}, {whole})")


def _pieces(text: str) -> str:
    for mark in MARKS:
        text = f"replace({text}, '{mark}', '{mark}\n')"
    parts = f"transform(split({text}, '\n'), p -> if(length(p) <= {LONG}, array(p), regexp_extract_all(p, '.{{1,{PART}}}', 0)))"
    return f"filter(flatten({parts}), p -> p != '')"


def _vector(pieces: str, lanes: int) -> str:
    return _bound(f"transform({pieces}, p -> xxhash64(p))", "own", f"named_struct('n', cast(size(own) as bigint), 'lanes', {_packed('own', lanes)})")


def lanes(text: str) -> Column:
    """struct of all vectors of ``text`` (SQL): wide array<bigint>; pieces and runs, each struct<n, lanes>.

    n is the number of pieces, lanes are packed four to a long; runs of a text that isn't short are 0 and have no lanes.
    """
    text = f"coalesce({text}, '')"
    padded = f"concat(' ', replace({text}, '\n', ' \n '), ' ')"
    none = "named_struct('n', 0L, 'lanes', cast(array() as array<bigint>))"
    runs = f"if(length({text}) <= {SHORT}, {_vector(f"regexp_extract_all({padded}, '(?=(.{{3}})).', 1)", SHORT_LANES)}, {none})"
    pieces = _vector(_pieces(text), LANES)
    return F.expr(f"named_struct('wide', {_wide(text)}, 'pieces', {pieces}, 'runs', {runs})")


def written(vectors: Column) -> Column:
    """Lower-case hex of ``lanes``."""

    def hexed(values: Column, digits: int) -> Column:
        return F.array_join(F.transform(values, lambda x: F.lpad(F.lower(F.hex(x)), digits, "0")), "")

    parts = [hexed(vectors["wide"], 8)]
    for k in ("pieces", "runs"):
        parts += [F.lpad(F.lower(F.hex(vectors[k]["n"])), 8, "0"), hexed(vectors[k]["lanes"], 16)]
    return F.concat(*parts)


def read(fingerprint: Column) -> Column:
    """``lanes`` of a written fingerprint."""
    number = lambda at: F.conv(F.substr(fingerprint, at, F.lit(8)), 16, 10).cast("long")
    whole = lambda at: F.shiftleft(number(at), 32).bitwiseOR(number(at + 8))

    def part(at: int, size: Column) -> Column:
        values = F.transform(F.sequence(F.lit(0), size - 1), lambda k: whole(F.lit(at + 8) + k * 16))
        return F.struct(number(F.lit(at)).alias("n"), F.when(size > 0, values).otherwise(F.array().cast("array<bigint>")).alias("lanes"))

    first = 8 * WIDE + 1
    second = first + 8 + 4 * LANES
    wide = F.transform(F.sequence(F.lit(0), F.lit(WIDE - 1)), lambda k: number(k * 8 + 1))
    rest = F.floor((F.length(fingerprint) - (second + 7)) / 16).cast("int")
    return F.struct(wide.alias("wide"), part(first, F.lit(LANES // 4)).alias("pieces"), part(second, rest).alias("runs"))


def fingerprint(text: str) -> Column:
    """Of ``text`` (SQL): equal texts, and texts of the same lines in another order, have the same one."""
    return written(lanes(text))


def _like(a: str, b: str) -> str:
    """1 - |a - b|^2 / (|a|^2 + |b|^2) of two vectors struct<n, lanes>, at least 0; 1 if both are empty."""
    # 2 * lane - n is known modulo 2^17.
    square = "pow(((({x}) * 2 - {n} + 65536) & 131071) - 65536, 2)"
    lane = "(shiftrightunsigned({x}, {k}) & 65535)"
    fields = [lane.format(x="{x}", k=16 * k) for k in range(4)]
    own = lambda of, n: f"aggregate({of}, 0D, (s, x) -> s + " + " + ".join(square.format(x=f.format(x="x"), n=n) for f in fields) + ")"
    both = " + ".join(square.format(x=f"{f.format(x='x')} - {f.format(x='y')}", n="(na - nb)") for f in fields)
    apart = f"aggregate(zip_with({a}.lanes, {b}.lanes, (x, y) -> {both}), 0D, (s, x) -> s + x)"
    share = _bound(apart, "apart", f"if(apart = 0, 1.0D, greatest(0.0D, 1 - apart / ({own(f'{a}.lanes', 'na')} + {own(f'{b}.lanes', 'nb')})))")
    share = _bound(f"{a}.n", "na", _bound(f"{b}.n", "nb", share))
    return f"case when {a}.n = 0 and {b}.n = 0 then 1.0D when {a}.n = 0 or {b}.n = 0 then 0.0D else {share} end"


def likeness(a: str, b: str) -> Column:
    """Share (0 to 1) of pieces that the texts of ``lanes`` a and b (columns) have in common, estimated; of runs if both are short."""
    both_short = f"size({a}.runs.lanes) > 0 and size({b}.runs.lanes) > 0"
    return F.expr(f"if({both_short}, {_like(f'{a}.runs', f'{b}.runs')}, {_like(f'{a}.pieces', f'{b}.pieces')})")


def with_next(docs: DataFrame) -> DataFrame:
    """(doc_id, text, fp, next_text, next_fp; fp are ``lanes``): each row with the one after it by descending doc_id, the last with the first.

    Ids of null come last; rows that repeat an id go by descending text. The order is made of ranges of the id between
    splitters (a bounded number), each sorted by itself; the last row of a range looks up the first of the next one.
    Texts are shuffled once.
    """
    spark = docs.sparkSession
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    low = F.coalesce("doc_id", F.lit(-(1 << 63)))
    ids = base.select(low.alias("id"))
    rows = ids.count()
    side = min(MAX_RANGES_SQRT, max(1, round((rows / ROWS_PER_RANGE) ** 0.5)))
    cuts = []
    if side > 1:
        n = side * side
        cuts = ids.agg(F.percentile_approx("id", [k / n for k in range(1, n)], 20 * n)).first()[0]
    cuts = sorted(set(cuts), reverse=True)
    coarse = cuts[::side]
    fine = [cuts[k : k + side] for k in range(0, len(cuts), side)] or [[]]

    def above(values: Column) -> Column:
        return F.size(F.filter(values, lambda s: s > F.col("id")))

    def ranged(df: DataFrame) -> DataFrame:
        df = df.withColumn("id", low)
        if not cuts:
            return df.withColumn("range", F.lit(0))
        c = df.withColumn("c", F.greatest(above(F.lit(coarse)), F.lit(1)))
        groups = F.array(*[F.lit(f) for f in fine])
        return c.withColumn("range", (F.col("c") - 1) * (side + 1) + above(groups[F.col("c") - 1])).drop("c")

    tops = ranged(base.select("doc_id")).groupBy("range").agg(F.max("id").alias("id")).collect()  # one row a range
    tops = [tuple(r) for r in sorted(tops, key=lambda r: r["range"])]
    following = [(tops[k][0], tops[(k + 1) % len(tops)][1]) for k in range(len(tops))]
    after = spark.createDataFrame(following, "range int, id long")
    wanted = F.broadcast(spark.createDataFrame([(i,) for i in sorted({x[1] for x in following})], "id long"))
    firsts = base.withColumn("id", low).join(wanted, "id").groupBy("id").agg(F.max("text").alias("first_text"))
    firsts = firsts.withColumn("first_fp", lanes("first_text"))
    after = after.join(firsts, "id").drop("id")
    # The fingerprint is made before the shuffle, once for each text.
    rows = ranged(base.withColumn("fp", lanes("text")))
    w = Window.partitionBy("range").orderBy(F.col("id").desc(), F.col("text").desc())
    rows = rows.select("range", "doc_id", "text", "fp", F.lead("text").over(w).alias("lead_text"), F.lead("fp").over(w).alias("lead_fp"))
    out = rows.join(after, "range")
    return out.select("doc_id", "text", "fp", F.coalesce("lead_text", "first_text").alias("next_text"), F.coalesce("lead_fp", "first_fp").alias("next_fp"))
