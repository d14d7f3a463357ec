"""Duplicate lines up to one word's edit, by a deletion-neighbourhood join, in DataFrame operations only.

A line is a duplicate if an earlier line, in the order of (doc_id, line number), has the
same words, or, where both have NEAR_WORDS words or more, words within one insertion,
deletion or substitution. The earliest such line is what it repeats. Lines of every
length that have a word are compared.

1. Lines are reduced to the distinct ones with their first places, by 128-bit hashes.
2. Of two lines within the bound, one half is the same word by word. A line of n words
   says its halves of n div 2 words under its length and those of (n - 1) div 2 words
   under the length below; lines of equal length meet under the former, a line meets one
   with a word less under both. Only lines that meet another one go on, with the sides
   on which they met and the kind of the edit. This drops no pair.
3. These lines' words are read again, and variants with one word deleted on the other
   side are emitted as hashed keys. A variant's hash is an exclusive or over words of
   hashes of (word, place): the words before the gap keep their place, those behind it
   move down by one, so running values give all variants in time n * sqrt(n).
4. Equal keys are joined through the group's smallest line: lines that agree after
   deleting the same place differ by a substitution, so the group's earliest is within
   the bound of all others; a line equal to another one's variant differs by a deletion.
   So no group is expanded into pairs, however many lines share a key.
5. The edit distance to the line found is verified on the words.

Where few of many rows go on, a bit table of fixed size leaves out most others before
a shuffle (``hashbits``); texts themselves are never shuffled.

Edge cases: null texts have no line, blank lines are left alone; lines of any length are
compared whole; rows that share a doc_id are one document, whose lines at the same place
aren't copies of each other unless their words differ by an edit (the smaller hash is
then the earlier one); a null doc_id comes first, others are whole numbers; extra
columns are ignored, also such as have the names used here; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidelabel.llm.common import documents, fresh, materialise
from tidelabel.llm.hashbits import hash_bits, perhaps_in, surely_not_in

#: Words from which on one edited word leaves a line a duplicate: with two, any change touches half of the line.
NEAR_WORDS = 3
#: White space but for line ends and blanks.
OTHER_WHITE = ("\t", "\u000b", "\u000c", "\r")
#: Ways in which a line met another: a substitution, a deletion from it, each with the front or the end shared; another line's deletion gives it.
SUB_FRONT, SUB_END, DEL_FRONT, DEL_END, WHOLE = 1, 2, 4, 8, 16
LINE = 1 << 31


def plain(line: str) -> str:
    """SQL: the words of a line joined by single blanks; other white space must be blanks already."""
    return f"trim(case when contains({line}, '  ') then regexp_replace({line}, ' {{2,}}', ' ') else {line} end)"


def blanked(text: str) -> str:
    """SQL: ``text`` with blanks for other white space; most texts have none, and asking is cheaper than replacing."""
    out = text
    for c in OTHER_WHITE:
        out = f"replace({out}, char({ord(c)}), ' ')"
    return f"case when {' or '.join(f'contains({text}, char({ord(c)}))' for c in OTHER_WHITE)} then {out} else {text} end"


def lines_of(docs: DataFrame) -> DataFrame:
    """(doc_id, line_no, line, h, g) of all lines with a word; h and g are a line's 128-bit hash."""
    rows = docs.select("doc_id", F.posexplode(F.split(F.expr(blanked("text")), "\n")).alias("line_no", "raw"))
    rows = rows.select("doc_id", "line_no", F.expr(plain("raw")).alias("line")).where("line <> ''")
    return rows.selectExpr("doc_id", "line_no", "line", "xxhash64(line) as h", "xxhash64('second', line) as g")


def place(doc_id: str = "doc_id", line_no: str = "line_no") -> str:
    """SQL: (doc_id, line number) as one number in their order; a null id is below all."""
    return f"coalesce(cast({doc_id} as decimal(20,0)), -9223372036854775809BD) * {LINE}BD + {line_no}"


def place_parts(at: str, kind: str) -> tuple[str, str]:
    """SQL: doc_id and line number of a place."""
    line = f"cast(pmod({at}, {LINE}BD) as int)"
    return f"case when {at} >= -9223372036854775808BD * {LINE}BD then cast(({at} - {line}) div {LINE}BD as {kind}) end", line


def halves_of(near_words: int) -> list[str]:
    """SQL columns (h0 .. h3) of a line's halves, by role: 0, 1 of its own length, 2, 3 of the one below; front, end."""
    front, end = "slice(words, 1, cast({0} as int))", "slice(words, n + 1 - cast({0} as int), cast({0} as int))"
    of = [f"xxhash64('{side}', {n}, {part.format(size)})" for size, n in (("n div 2", "n"), ("(n - 1) div 2", "n - 1")) for side, part in (("f", front), ("e", end))]
    return [f"case when n >= {near_words} then {x} end as h{role}" for role, x in enumerate(of)]


def ways_met(distinct: DataFrame) -> DataFrame:
    """(h, ways): lines that share a half with another one of fitting length."""
    halves = distinct.where("h0 is not null").selectExpr("h", "posexplode(array(h0, h1, h2, h3)) as (role, half)")
    groups = halves.groupBy("half").agg(F.sum(F.expr("case when role < 2 then 1L else 0L end")).alias("same"), F.sum(F.expr("case when role < 2 then 0L else 1L end")).alias("longer"))
    groups = materialise(groups.where("same > 1 or (same > 0 and longer > 0)"), "line-halves")
    met = perhaps_in(halves, "half", hash_bits(groups, "half")).join(groups, "half")
    way = f"""case when role < 2 then (case when same > 1 then shiftleft({SUB_FRONT}L, role) else 0L end) | (case when longer > 0 then {WHOLE}L else 0L end)
        when same > 0 then shiftleft({DEL_FRONT}L, role - 2) else 0L end"""
    return met.selectExpr("h", f"{way} as way").where("way <> 0").groupBy("h").agg(F.expr("bit_or(way)").alias("ways"))


def variants(near: DataFrame) -> DataFrame:
    """(key, id, kind) of lines (id, line, ways): kind 0 is a line itself, 1 a word deleted, 2 a word deleted at a known place.

    A line's hash is the exclusive or of ``stays``; with word i deleted, it is that of
    the ``moves`` but the i-th and, for the words before, of ``shift`` = stays ^ moves.
    These running values are made from sums of blocks of about sqrt(n) words.
    """
    rows = near.repartition("id").select("id", "ways", F.split("line", " ").alias("words"))
    rows = rows.selectExpr("id", "ways", "transform(words, (w, i) -> xxhash64(w, i)) as stays", "transform(words, (w, i) -> xxhash64(w, i - 1)) as moves")
    all_of = lambda a, start="0L": f"aggregate({a}, {start}, (a, x) -> a ^ x)"
    rows = rows.selectExpr("id", "ways", "size(stays) as n", f"{all_of('stays')} as whole", f"{all_of('moves')} as moved", "moves", "zip_with(stays, moves, (x, y) -> x ^ y) as shift", "cast(ceil(sqrt(size(stays))) as int) as b")
    rows = rows.withColumn("blocks", F.expr(f"transform(sequence(0, cast((n - 1) div b as int)), k -> {all_of('slice(shift, k * b + 1, b)')})"))
    rows = rows.withColumn("starts", F.expr(f"transform(blocks, (x, k) -> {all_of('slice(blocks, 1, k)')})"))
    before = all_of("slice(shift, i - i % b + 1, i % b)", "starts[cast(i div b as int)]")
    gaps = rows.selectExpr("id", "ways", "n", "whole", f"posexplode(transform(moves, (m, i) -> moved ^ m ^ {before})) as (i, gap)")
    wanted = lambda f, e, size: f"((ways & {f}) <> 0 and i >= {size} or (ways & {e}) <> 0 and i < n - {size})"
    keys = gaps.selectExpr("id", f"""stack(3,
        0, case when i = 0 and (ways & {WHOLE}) <> 0 then xxhash64(whole, n) end,
        1, case when {wanted(DEL_FRONT, DEL_END, '((n - 1) div 2)')} then xxhash64(gap, n - 1) end,
        2, case when {wanted(SUB_FRONT, SUB_END, '(n div 2)')} then xxhash64(gap, n - 1, i) end) as (kind, key)""")
    return keys.where("key is not null").select("key", "id", "kind")


def neighbours(near: DataFrame) -> DataFrame:
    """(id, to): the smallest line one deletion or substitution away and before it."""
    keys = materialise(variants(near), "line-variants")
    groups = keys.groupBy("key").agg(F.min(F.expr("case when kind = 0 then id end")).alias("itself"), F.min(F.expr("case when kind <> 0 then id end")).alias("other"), F.max("kind").alias("kinds"), F.count("*").alias("members"))
    groups = groups.where("members > 1 and (kinds = 2 or itself is not null and other is not null)").select("key", "itself", "other")
    groups = materialise(groups, "line-groups")
    met = perhaps_in(keys, "key", hash_bits(groups, "key")).join(groups, "key")
    return met.selectExpr("id", "case kind when 1 then itself else other end as to").where("to < id").groupBy("id").agg(F.min("to").alias("to"))


def within_one_edit(a: str, b: str) -> str:
    """SQL condition: word arrays a and b are at most one insertion, deletion or substitution apart."""
    shared = lambda x, y: f"(coalesce(nullif(array_position(zip_with({x}, {y}, (p, q) -> p <=> q), false), 0), greatest(size({x}), size({y})) + 1) - 1)"
    return f"(abs(size({a}) - size({b})) <= 1 and {shared(a, b)} + {shared(f'reverse({a})', f'reverse({b})')} >= greatest(size({a}), size({b})) - 1)"


def duplicate_lines(docs: DataFrame, near_words: int = NEAR_WORDS) -> DataFrame:
    """(doc_id, line_no, first_doc_id, first_line_no, edits, line_hash): one row per line that repeats an earlier one."""
    docs = docs.select("doc_id", "text")
    kind = docs.schema["doc_id"].dataType.simpleString()
    worded = lines_of(docs).selectExpr("doc_id", "line_no", "h", "g", "split(line, ' ') as words").withColumn("n", F.size("words"))
    lines = materialise(worded.selectExpr("doc_id", "line_no", "h", "g", *halves_of(near_words)), "lines")
    halves = [F.min(f"h{role}").alias(f"h{role}") for role in range(4)]
    distinct = lines.groupBy("h", "g").agg(F.min(F.expr(place())).alias("at"), F.count("*").alias("copies"), *halves)
    distinct = materialise(distinct, "distinct-lines")
    met = materialise(ways_met(distinct), "met-lines")
    # the words of each met line, read at its first place
    firsts = perhaps_in(distinct.select("h", "g", "at"), "h", hash_bits(met, "h")).join(met, "h")
    owner = F.expr(place_parts("at", kind)[0])
    firsts = materialise(firsts.withColumn("spot", F.xxhash64("h", "g", "at")).withColumn("owner", F.xxhash64(owner)), "met-line-places")
    owned = perhaps_in(docs.withColumn("owner", F.xxhash64("doc_id")), "owner", hash_bits(firsts, "owner"))
    texts = lines_of(owned).withColumn("at", F.expr(place())).withColumn("spot", F.xxhash64("h", "g", "at"))
    texts = perhaps_in(texts, "spot", hash_bits(firsts, "spot")).drop("spot", "doc_id", "line_no")
    near = texts.join(firsts.drop("spot", "owner"), ["h", "g", "at"]).dropDuplicates(["h", "g"])
    near = materialise(near.orderBy("at", "h", "g").withColumn("id", F.monotonically_increasing_id()), "near-lines")
    offered = neighbours(near).join(near.select("id", "h", "g", "line"), "id")
    other = near.select(F.col("id").alias("to"), F.col("at").alias("to_at"), F.col("line").alias("to_line"))
    apart = within_one_edit("split(line, ' ')", "split(to_line, ' ')")
    verified = offered.join(other, "to").where(apart).select("h", "g", "to_at")
    repeated = distinct.select("h", "g", "at", "copies").join(verified, ["h", "g"], "left").where("copies > 1 or to_at is not null")
    repeated = materialise(repeated.drop("copies"), "repeated-lines")
    rows = perhaps_in(lines.select("doc_id", "line_no", "h", "g"), "h", hash_bits(repeated, "h")).join(repeated, ["h", "g"])
    first_doc, first_line = place_parts("coalesce(to_at, at)", kind)
    rows = rows.where(f"to_at is not null or {place()} <> at")
    return rows.selectExpr("doc_id", "line_no", f"{first_doc} as first_doc_id", f"{first_line} as first_line_no", "case when to_at is null then 0 else 1 end as edits", "h as line_hash")


def without_duplicate_lines(docs: DataFrame, duplicates: DataFrame) -> DataFrame:
    """``docs`` less the duplicate lines, with n_chars set anew; documents left blank by that go.

    A line is removed by its document, number and hash, so rows that share an id lose only
    lines of their own. Texts without a duplicate line aren't shuffled.
    """
    code = lambda line_no, h: f"(shiftleft(cast({line_no} as bigint), 32) | ({h} & 4294967295L))"
    owner, removed, key, before = (fresh(docs, name) for name in ("owner", "removed", "owner_key", "before"))
    gone = duplicates.select(F.col("doc_id").alias(owner), F.expr(code("line_no", "line_hash")).alias(removed)).groupBy(owner).agg(F.collect_set(removed).alias(removed))
    gone = materialise(gone, "removed-lines")
    bits = hash_bits(gone.select(F.xxhash64(owner).alias("k")), "k")
    keyed = docs.withColumn(key, F.xxhash64("doc_id"))
    rows = perhaps_in(keyed, key, bits).join(gone, F.col("doc_id").eqNullSafe(F.col(owner)), "left")
    hashes = f"transform(split({blanked('text')}, '\\n'), l -> xxhash64({plain('l')}))"
    kept = f"array_except(transform({hashes}, (h, i) -> {code('i', 'h')}), {removed})"
    left = F.expr(f"transform(array(split(text, '\n')), ls -> array_join(transform({kept}, c -> ls[cast(shiftright(c, 32) as int)]), '\n'))[0]")
    rows = rows.withColumn(before, F.col("text")).withColumn("text", F.when(F.col(removed).isNull(), F.col("text")).otherwise(left))
    rows = rows.where(F.col("text").eqNullSafe(F.col(before)) | (F.length(F.translate("text", " \t\n\x0b\x0c\r", "")) > 0))
    if "n_chars" in docs.columns:
        rows = rows.withColumn("n_chars", F.when(F.col(removed).isNull(), F.col("n_chars")).otherwise(F.length("text")).cast(docs.schema["n_chars"].dataType))
    return surely_not_in(keyed, key, bits).select(*docs.columns).union(rows.select(*docs.columns))


def op7_deletion_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return duplicate_lines(documents(spark, sf_dir)).drop("line_hash")


ORACLE = r"""
with l as (select doc_id, unnest(string_split(text, chr(10))) as line, unnest(range(len(string_split(text, chr(10))))) as line_no from documents),
w as (select doc_id, line_no, list_filter(string_split_regex(line, '[\x20\x09-\x0D]+'), lambda x: x <> '') as words from l),
k as (select doc_id, line_no, words, len(words) as n from w where len(words) > 0),
d as (select words, any_value(n) as n, min({'d': doc_id, 'l': line_no}) as p0 from k group by words),
b as (select distinct p0, words, n, unnest([
        {'s': 0, 'w': words[1:n // 2]}, {'s': 0, 'w': words[1:(n - 1) // 2]},
        {'s': 1, 'w': words[n - n // 2 + 1:n]}, {'s': 1, 'w': words[n - (n - 1) // 2 + 1:n]}]) as half from d where n >= 3),
c as (select distinct x.p0 as p0, y.p0 as p1, x.words as a, y.words as b, x.n as na, y.n as nb from b x join b y on x.half = y.half and y.p0 < x.p0 and abs(x.n - y.n) <= 1),
s as (select p0, p1, na, nb,
        coalesce(list_min(list_filter(range(1, greatest(na, nb) + 1), lambda i: a[i] is distinct from b[i])), greatest(na, nb) + 1) - 1 as f,
        coalesce(list_min(list_filter(range(1, greatest(na, nb) + 1), lambda i: list_reverse(a)[i] is distinct from list_reverse(b)[i])), greatest(na, nb) + 1) - 1 as e from c),
v as (select p0, min(p1) as p1 from s where f + e >= greatest(na, nb) - 1 group by p0)
select k.doc_id, cast(k.line_no as integer) as line_no, coalesce(v.p1, d.p0).d as first_doc_id, cast(coalesce(v.p1, d.p0).l as integer) as first_line_no,
  cast(case when v.p1 is null then 0 else 1 end as integer) as edits
from k join d using (words) left join v on v.p0 = d.p0
where v.p1 is not null or {'d': k.doc_id, 'l': k.line_no} <> d.p0
"""
