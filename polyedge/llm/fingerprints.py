"""Document fingerprints: invertible Bloom lookup sketches of paragraph digests, native SQL only.

A paragraph is a line, cut after the sentence end that follows its 120th character if it is longer,
or at its 520th character where no sentence ends before.
Its digest is the XXH64 of its text; a document is the set of its digests.  A sketch adds every
digest to three of 24 cells (one in each of three tables), each cell holding the number, the XOR
of digests and the XOR of their check hashes.  Sketches of two versions subtract cell by cell; what
both hold cancels, and peeling takes digests out of cells that hold a single one until none is
left.  If cells remain, the sketch was too small: the digests are dealt by hash to as many sketches
as about six digests each need.  Should one of these fail, all are dealt again by another hash to four
times as many, and so on: each retry fails with a chance of a few in a hundred, independently, and no
pair of texts is expected to need the last of ``RETRIES``; what would is compared as sets.

The fingerprint is the text form of the first, 24-cell sketch.  Likeness is shared digests over all
digests of the two sets (1.0 for two empty ones), from the numbers of recovered digests.

Defined results: a null text is the empty one; the empty text has no digest; order and repetition
of paragraphs do not count; of rows with equal ids, the one whose text sorts first comes first.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

PARAGRAPH = r"[^\n]{1,120}[^\n.!?]{0,400}[.!?]*\n?|\n"
TABLES, PER_TABLE = 3, 8
CELLS = TABLES * PER_TABLE
ROUNDS = 24
RETRIES = 8
ZERO = "named_struct('n', 0, 'k', 0L, 'c', 0L)"


def let(name: str, value: str, body: str) -> str:
    """SQL that evaluates ``value`` once and names it within ``body``."""
    return f"get(transform(array({value}), {name} -> {body}), 0)"


def digests(text: str) -> str:
    pattern = PARAGRAPH.replace("\\", "\\\\")
    return f"array_distinct(transform(regexp_extract_all({text}, '{pattern}', 0), p -> xxhash64(p)))"


def item(k: str, seed: str, n: str = "1") -> str:
    """Sign, digest, check hash, hash that deals items to sketches, and a bit mask of the cells, one in each table."""
    place = " | ".join(f"shiftleft(1, {PER_TABLE * t} + cast(shiftrightunsigned(h, 3 * {t}) & {PER_TABLE - 1} as int))" for t in range(TABLES))
    return let("h", f"xxhash64({k}, {seed})", f"named_struct('n', {n}, 'k', {k}, 'c', xxhash64({k}, 1), 'h', h, 'm', {place})")


def items(digest_array: str, seed: str = "2", n: str = "1") -> str:
    return f"transform({digest_array}, k -> {item('k', seed, n)})"


def cells(item_array: str) -> str:
    return (
        f"transform(sequence(0, {CELLS - 1}), j -> aggregate(filter({item_array}, x -> getbit(x.m, j) = 1), {ZERO}, "
        "(a, x) -> named_struct('n', a.n + x.n, 'k', a.k ^ x.k, 'c', a.c ^ x.c)))"
    )


def subtract(a: str, b: str) -> str:
    return f"zip_with({a}, {b}, (x, y) -> named_struct('n', x.n - y.n, 'k', x.k ^ y.k, 'c', x.c ^ y.c))"


def peel(cell_array: str) -> str:
    """Struct of the digests only in the first (``plus``) and only in the second (``minus``), and ``ok``."""
    none = "cast(array() as array<bigint>)"
    start = f"named_struct('cells', {cell_array}, 'plus', {none}, 'minus', {none}, 'more', true)"
    single = "array_distinct(transform(filter(s.cells, c -> abs(c.n) = 1 AND c.c = xxhash64(c.k, 1)), c -> " + item("c.k", "w.seed", "c.n") + "))"
    keys = lambda sign: f"transform(filter(found, p -> p.n {sign} 0), p -> p.k)"
    without = f"transform(s.cells, (c, j) -> aggregate(filter(found, p -> getbit(p.m, j) = 1), c, (t, p) -> named_struct('n', t.n - p.n, 'k', t.k ^ p.k, 'c', t.c ^ p.c)))"
    take = f"named_struct('cells', {without}, 'plus', concat(s.plus, {keys('>')}), 'minus', concat(s.minus, {keys('<')}), 'more', true)"
    stop = "named_struct('cells', s.cells, 'plus', s.plus, 'minus', s.minus, 'more', false)"
    one = f"CASE WHEN NOT s.more THEN s ELSE {let('found', single, f'CASE WHEN size(found) = 0 THEN {stop} ELSE {take} END')} END"
    done = "s -> named_struct('plus', s.plus, 'minus', s.minus, 'ok', forall(s.cells, c -> c.n = 0 AND c.k = 0L))"
    return f"aggregate(sequence(1, {ROUNDS}), {start}, (s, i) -> {one}, {done})"


def peel_dealt(a: str, b: str, retry: str) -> str:
    """Peel with the digests dealt to many sketches: coarse parts first, so long texts stay linear."""
    seed = f"cast({retry} + 3 as int)"
    both = f"concat({items(f'transform({a}, x -> x.k)', seed)}, {items(f'transform({b}, x -> x.k)', seed, '-1')})"
    parts = f"named_struct('seed', {seed}, 'g', cast(greatest(1, ceil(pow(2, {retry}) * sqrt((size({a}) + size({b})) / 6.0))) as bigint), 'x', {both})"
    empty = "named_struct('plus', cast(array() as array<bigint>), 'minus', cast(array() as array<bigint>), 'ok', true)"
    join = "named_struct('plus', concat(m.plus, r.plus), 'minus', concat(m.minus, r.minus), 'ok', r.ok)"
    one = let("q", "filter(o, x -> pmod(shiftrightunsigned(x.h, 40), w.g) = v)", f"CASE WHEN size(q) = 0 THEN m ELSE {let('r', peel(cells('q')), join)} END")
    over_fine = f"aggregate(sequence(0L, w.g - 1L), m0, (m, v) -> CASE WHEN m.ok THEN {one} ELSE m END)"
    over_coarse = f"aggregate(sequence(0L, w.g - 1L), {empty}, (m0, u) -> CASE WHEN m0.ok THEN " + let("o", "filter(w.x, x -> pmod(shiftrightunsigned(x.h, 20), w.g) = u)", f"CASE WHEN size(o) = 0 THEN m0 ELSE {over_fine} END") + " ELSE m0 END)"
    return let("w", parts, over_coarse)


def difference(a: str, b: str, a_cells: str, b_cells: str) -> str:
    """Digests only in ``a`` and only in ``b``, and ``tries``: small sketch (0), then larger ones until one peels, then sets."""
    of = lambda d, tries: f"named_struct('plus', {d}.plus, 'minus', {d}.minus, 'ok', {d}.ok, 'tries', {tries})"
    first = let("w", "named_struct('seed', 2)", peel(subtract(a_cells, b_cells)))
    larger = f"aggregate(sequence(0, {RETRIES - 1}), {let('d0', first, of('d0', '0'))}, (d, t) -> CASE WHEN d.ok THEN d ELSE {let('d1', peel_dealt(a, b, 't'), of('d1', 't + 1'))} END)"
    by_sets = f"named_struct('plus', array_except(transform({a}, x -> x.k), transform({b}, x -> x.k)), 'minus', array_except(transform({b}, x -> x.k), transform({a}, x -> x.k)), 'ok', true, 'tries', {RETRIES + 1})"
    return let("d9", larger, f"CASE WHEN d9.ok THEN d9 ELSE {by_sets} END")


def likeness(diff: str, a: str, b: str) -> str:
    n, d = f"(size({a}) + size({b}))", f"(size({diff}.plus) + size({diff}.minus))"
    return f"CASE WHEN {n} = 0 THEN 1D ELSE ({n} - {d}) / cast({n} + {d} as double) END"


def text_form(cell_array: str, item_array: str) -> str:
    cell = "concat(hex(c.n), ':', lower(hex(c.k)), ':', lower(hex(c.c)))"
    return f"concat(cast(size({item_array}) as string), '/', array_join(transform({cell_array}, c -> {cell}), ','))"


def version_difference(df: DataFrame, old: str, new: str) -> DataFrame:
    """Append ``removed`` and ``added`` (paragraph digests), ``likeness`` of two text columns and ``tries``,
    the number of larger sketches that were needed."""
    body = let("f", "named_struct('a', " + cells("e.a") + ", 'b', " + cells("e.b") + ")", let("d", difference("e.a", "e.b", "f.a", "f.b"), f"named_struct('removed', d.plus, 'added', d.minus, 'likeness', {likeness('d', 'e.a', 'e.b')}, 'tries', d.tries)"))
    made = let("e", f"named_struct('a', {items(digests(_text(old)))}, 'b', {items(digests(_text(new)))})", body)
    kept = [F.col(f"`{c}`") for c in df.columns if c.lower() not in ("removed", "added", "likeness", "tries")]
    return df.select(*kept, F.expr(made).alias("__v")).select(*kept, "__v.removed", "__v.added", "__v.likeness", "__v.tries")


def _text(name: str) -> str:
    return f"coalesce(cast(`{name}` as string), '')"


def _bucket(ids: Column, bounds: list) -> Column:
    """Number of the last bound at or below the id (binary search; nulls go to the first)."""
    arr = F.array(*[F.lit(b) for b in bounds]) if len(bounds) < 2 else F.lit(bounds)
    steps = max(1, len(bounds).bit_length())
    start = F.struct(F.lit(0).alias("lo"), F.lit(len(bounds)).alias("hi"))

    def step(s: Column, _: Column) -> Column:
        mid = F.floor((s["lo"] + s["hi"]) / 2).cast("int")
        up = F.coalesce(F.get(arr, mid) <= ids, F.lit(False))
        return F.when(s["hi"] - s["lo"] <= 1, s).otherwise(F.struct(F.when(up, mid).otherwise(s["lo"]).alias("lo"), F.when(up, s["hi"]).otherwise(mid).alias("hi")))

    return F.aggregate(F.sequence(F.lit(1), F.lit(steps)), start, step)["lo"]


def with_next(rows: DataFrame, id_col: str, columns: list[str], tie: str, buckets: int | None = None) -> DataFrame:
    """Append ``next_<c>`` of the row that follows by ascending id; after the last comes the first.

    Rows are dealt to id ranges whose bounds are ids of the table; the first row of each range is
    also sent to the range before it (and the first of all to the last), so a window inside each
    range sees every successor and no row needs a global order in one task.
    """
    spark = rows.sparkSession
    n = buckets or 8 * int(spark.conf.get("spark.sql.shuffle.partitions"))
    n = min(n, 65_536)
    got = rows.agg(F.count("*"), F.count(F.lit(1)) - F.count(id_col), F.min(id_col), F.percentile_approx(id_col, [i / n for i in range(n)], 20 * n)).first()
    if not got[0]:
        return rows.select("*", *[F.col(c).alias(f"next_{c}") for c in columns])
    nulls, low = got[1], got[2]
    bounds = sorted({low, *(got[3] or [])}) if low is not None else []
    if not bounds:
        bounds = [0]
    last = len(bounds) - 1
    ids = F.col(id_col)
    own = _bucket(ids, bounds)
    first = ids.isNull() if nulls else ids == F.lit(low)
    starts = F.coalesce(F.get(F.lit(bounds) if last else F.array(F.lit(bounds[0])), F.col("__b")) == ids, F.lit(False)) & (F.col("__b") > 0)
    part = lambda b, wrap, halo: F.struct(b.cast("int").alias("b"), F.lit(wrap).alias("w"), F.lit(halo).alias("h"))
    places = F.array(part(F.col("__b"), 0, False))
    places = F.concat(places, F.when(starts, F.array(part(F.col("__b") - 1, 0, True))).otherwise(F.array().cast("array<struct<b:int,w:int,h:boolean>>")))
    places = F.concat(places, F.when(first, F.array(part(F.lit(last), 1, True))).otherwise(F.array().cast("array<struct<b:int,w:int,h:boolean>>")))
    dealt = rows.withColumn("__b", own).withColumn("__p", F.explode(places))
    win = Window.partitionBy("__p.b").orderBy("__p.w", F.col(id_col).asc_nulls_first(), tie)
    out = dealt.select(*[F.col(c) for c in rows.columns], F.col("__p.h").alias("__h"), *[F.lead(c).over(win).alias(f"next_{c}") for c in columns])
    return out.where(~F.col("__h")).drop("__h")


def edit_and_fingerprint(docs: DataFrame, buckets: int | None = None) -> DataFrame:
    """Fingerprints of every text, of its edited text (second half from the next document's start), and their likeness."""
    rows = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    rows = rows.withColumn("dig", F.expr(digests("text")))
    pairs = with_next(rows, "doc_id", ["text", "dig"], "text", buckets)
    n = "char_length(text)"
    edited = f"concat(substring(text, 1, {n} - {n} div 2), substring(next_text, 1, cast({n} div 2 as int)))"
    result = (
        f"named_struct('sha', sha2(cast(e.t as binary), 256), 'fp', {text_form('f.a', 'i.a')}, 'efp', {text_form('f.e', 'i.e')}, "
        f"'ne', {let('d', difference('i.a', 'i.e', 'f.a', 'f.e'), likeness('d', 'i.a', 'i.e'))}, "
        f"'nn', {let('d', difference('i.a', 'i.n', 'f.a', 'f.n'), likeness('d', 'i.a', 'i.n'))})"
    )
    sketches = let("f", f"named_struct('a', {cells('i.a')}, 'e', {cells('i.e')}, 'n', {cells('i.n')})", result)
    sets = let("i", f"named_struct('a', {items('dig')}, 'e', {items(digests('e.t'))}, 'n', {items('next_dig')})", sketches)
    made = let("e", f"named_struct('t', {edited})", sets)
    return pairs.select("doc_id", F.expr(f"cast({n} as bigint)").alias("n_chars"), F.expr(made).alias("r")).select(
        "doc_id", "n_chars", F.col("r.sha").alias("edited_sha256"), F.col("r.fp").alias("fingerprint"), F.col("r.efp").alias("edited_fingerprint"), F.col("r.ne").alias("near_edited"), F.col("r.nn").alias("near_next")
    )
