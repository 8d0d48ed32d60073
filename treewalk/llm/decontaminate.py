"""Benchmark decontamination with spaced seeds, in DataFrame functions only.

Words are lower-cased runs of letters and digits.  A spaced seed is a mask over ``SPAN`` words
that keeps every third position and ignores the others; a masked window is hashed from its kept
words, so a hit survives any change at the ignored ones.  The three masks share no position, so fewer
changed words in a window than there are masks leave one mask untouched: whatever the
verification accepts (``SPAN - AGREE`` changes at most) is hit.  As each mask is the first one shifted
by a word, one array of hashes, a window at every word, serves all three.  Windows of the benchmark
and of the documents meet by hash.  A hit fixes an alignment (document, item, offset); every alignment is
then verified on the words themselves: over each stretch of ``SPAN`` aligned words around the hit, at
least ``AGREE`` words must agree at their places.  Items shorter than ``SPAN`` words are compared
as a whole, word for word.

The benchmark's side is broadcast only if its window count is under ``SMALL``; otherwise both
sides are shuffled.  Windows are equal-joined on 64-bit hashes; nothing is compared in pairs.

Defined cases: null and empty texts on either side match nothing; very long texts are matched
whole; repeated items are reported each; rows with null or repeated ids are told apart and each is
judged by its own text; an empty table on either side gives every document as clean (or no
rows); other columns of the inputs stay untouched and take no part, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, fresh_name, numbered, renamed

#: Fixed parameters: the span of a seed, and for each mask the places it keeps (all others are
#: ignored).  The masks are disjoint and one more than the changes that ``AGREE`` allows.
SPAN, AGREE, SMALL = 13, 11, 200_000
MASKS = ((0, 3, 6, 9), (1, 4, 7, 10), (2, 5, 8, 11))
REACH = MASKS[0][-1] + 1  # words that one mask spans


def words(text: Column) -> Column:
    """Lower-cased words of a text; null gives an empty array."""
    return F.array_remove(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), "")


def _hashes(tokens: Column) -> Column:
    return F.transform(tokens, lambda w: F.xxhash64(w))


def _window(h: Column):
    return lambda i: F.xxhash64(*[F.get(h, i + j) for j in MASKS[0]])


def _whole(h: Column, k: int):
    """Hash of ``k`` words in a row, for items of ``k`` words (seed -k)."""
    return lambda i: F.xxhash64(F.lit(-k), *[F.get(h, i + j) for j in range(k)])


def _starts(n: Column, least: int, k: int) -> Column:
    return F.when(n >= least, F.sequence(F.lit(0), n - k)).otherwise(F.array().cast("array<int>"))


def _hash_windows(h: Column, lengths: list[int]) -> Column:
    """Hashes of all windows in one array: masked ones, then by length for short items, whose seed
    is part of the hash, so a plain long is the whole key."""
    n = F.size(h)
    return F.concat(F.transform(_starts(n, SPAN, REACH), _window(h)), *[F.transform(_starts(n, k, k), _whole(h, k)) for k in lengths])


def _place(pos: Column, n: Column, seed: Column, lengths: list[int]) -> Column:
    """Start of the window at ``pos`` of the array that ``_hash_windows`` makes."""
    at, base = pos, F.when(n >= SPAN, n - REACH + 1).otherwise(F.lit(0))
    for k in lengths:
        at = F.when(seed == -k, pos - base).otherwise(at)
        base = base + F.greatest(n - (k - 1), F.lit(0))
    return at


def overlaps(docs: DataFrame, items: DataFrame) -> DataFrame:
    """Verified alignments ``(row, item_id, shift, agree, from, to)`` of ``docs (row, text)``: words
    ``from``..``to`` of the document lie in stretches that agree with the item."""
    d = docs.select("row", words(F.col("text")).alias("w"))
    b = items.select(F.col("item_id").cast("long").alias("item_id"), words(F.col("text").cast("string")).alias("w")).where("size(w) > 0").withColumn("item", F.monotonically_increasing_id())
    b = cut(b, "benchmark-words")  # numbers the items once: ids may be null or repeated
    sizes = b.select("item", _hashes(F.col("w")).alias("h")).select("*", F.size("h").alias("n"))
    lengths = sorted(r.n for r in sizes.where(F.col("n") < SPAN).select("n").distinct().collect())  # at most SPAN - 1
    tests = sizes.where(F.col("n") >= SPAN).select("item", F.posexplode(_hash_windows(F.col("h"), [])).alias("item_at", "hash")).select("item", "item_at", F.lit(0).alias("seed"), "hash")
    for k in lengths:
        tests = tests.union(sizes.where(F.col("n") == k).select("item", F.lit(0), F.lit(-k), _whole(F.col("h"), k)(F.lit(0))))
    n_tests = tests.count()
    keys = tests.groupBy("hash").agg(F.collect_list(F.struct("item", "item_at", "seed")).alias("where"))
    small = n_tests <= SMALL
    if small:
        keys = F.broadcast(keys)
    hashed = d.select("row", _hashes(F.col("w")).alias("h"))
    windows = hashed.select("row", F.size("h").alias("n"), F.posexplode(_hash_windows(F.col("h"), lengths)).alias("pos", "hash"))
    met = windows.join(keys, "hash").select("row", "n", "pos", F.explode("where").alias("x"))
    hits = met.select("row", F.col("x.item").alias("item"), (_place(F.col("pos"), F.col("n"), F.col("x.seed"), lengths) - F.col("x.item_at")).alias("shift"))
    lines = hits.distinct()
    texts = b.select("item", "item_id", F.col("w").alias("v"))
    aligned = lines.join(F.broadcast(texts) if small else texts, "item")
    both = d.join(aligned, "row")
    lo, hi = F.greatest(F.lit(0), -F.col("shift")), F.least(F.size("v"), F.size("w") - F.col("shift"))
    span = F.least(F.lit(SPAN), F.size("v"))
    need = F.when(span < SPAN, span).otherwise(F.lit(AGREE))
    same = F.transform(F.sequence(F.col("lo"), F.col("hi") - 1), lambda i: F.when(F.get(F.col("v"), i) == F.get(F.col("w"), i + F.col("shift")), 1).otherwise(0))
    counts = F.transform(F.sequence(F.lit(0), F.size("same") - F.col("span")), lambda i: F.aggregate(F.slice(F.col("same"), i + 1, F.col("span")), F.lit(0), lambda a, x: a + x))
    good = F.filter(F.transform(F.col("counts"), lambda c, i: F.when(c >= F.col("need"), i)), lambda i: i.isNotNull())
    checked = (
        both.select("row", "item_id", "shift", "w", "v", lo.alias("lo"), hi.alias("hi"), span.alias("span"), need.alias("need"))
        .where("hi - lo >= span")
        .withColumn("same", same)
        .withColumn("counts", counts)
        .withColumn("good", good)
        .where("size(good) > 0")
    )
    first = F.col("lo") + F.col("shift")
    return checked.select("row", "item_id", "shift", F.array_max("counts").alias("agree"), (first + F.array_min("good")).alias("from"), (first + F.array_max("good") + F.col("span") - 1).alias("to"))


def flag(docs: DataFrame, items: DataFrame) -> DataFrame:
    """``(doc_id, contaminated, n_items, item_ids)`` for every row of ``docs``."""
    rows, names = numbered(docs)
    found = overlaps(rows, items).groupBy("row").agg(F.array_sort(F.collect_set("item_id")).alias("item_ids"), F.lit(True).alias("contaminated"))
    ids = F.coalesce("item_ids", F.array().cast("array<bigint>"))
    out = rows.select("row").join(found, "row", "left")
    return renamed(out.select("row", F.coalesce("contaminated", F.lit(False)).alias("contaminated"), F.size(ids).cast("long").alias("n_items"), ids.alias("item_ids")), names)


def clean(docs: DataFrame, items: DataFrame) -> DataFrame:
    """Rows of ``docs`` (all columns) that hold no benchmark passage."""
    fixed, key = docs, "doc_id"
    if numbered(docs)[1] is not None:
        key = fresh_name(docs, "row")
        fixed = cut(docs.withColumn(key, F.monotonically_increasing_id()), "decontaminate-rows")
    name = fresh_name(fixed, "bad")
    rows = fixed.select(F.col(key).cast("long").alias("row"), F.col("text").cast("string").alias("text"))
    bad = overlaps(rows, items).select(F.col("row").alias(name)).distinct()
    return fixed.join(bad, F.col(key).cast("long") == F.col(name), "left_anti").select(*docs.columns)


_WORDS = "list_filter(string_split_regex(lower(coalesce(text, '')), '[^\\p{L}\\p{N}]+'), lambda x: x <> '')"

#: DuckDB SQL with the same rule: seeds as texts, and each alignment verified word by word.
ORACLE = f"""WITH d AS (SELECT doc_id, {_WORDS} AS w FROM documents), b AS (SELECT item_id, {_WORDS} AS v FROM benchmark),
 dk AS (SELECT doc_id, i, concat_ws(' ', w[i + 1], w[i + 4], w[i + 7], w[i + 10]) AS k FROM (SELECT *, unnest(range(len(w) - 9)) AS i FROM d WHERE len(w) >= {SPAN})),
 bk AS (SELECT item_id, i, concat_ws(' ', v[i + 1], v[i + 4], v[i + 7], v[i + 10]) AS k FROM (SELECT *, unnest(range(len(v) - 9)) AS i FROM b WHERE len(v) >= {SPAN})),
 hits AS (SELECT DISTINCT doc_id, item_id, dk.i - bk.i AS shift FROM dk JOIN bk USING (k)),
 lined AS (SELECT doc_id, item_id, shift, w, v, unnest(range(greatest(0, -shift), least(len(v), len(w) - shift) - {SPAN - 1})) AS i FROM hits JOIN d USING (doc_id) JOIN b USING (item_id)),
 long AS (SELECT DISTINCT doc_id, item_id FROM lined WHERE list_sum(list_transform(range({SPAN}), lambda j: CASE WHEN v[i + j + 1] = w[i + j + 1 + shift] THEN 1 ELSE 0 END)) >= {AGREE}),
 short AS (SELECT DISTINCT doc_id, item_id FROM d JOIN b ON len(v) BETWEEN 1 AND {SPAN - 1} AND contains(' ' || array_to_string(w, ' ') || ' ', ' ' || array_to_string(v, ' ') || ' ')),
 every AS (SELECT doc_id, list_sort(list(DISTINCT item_id)) AS ids FROM (SELECT * FROM long UNION SELECT * FROM short) GROUP BY doc_id)
 SELECT doc_id, ids IS NOT NULL AS contaminated, coalesce(len(ids), 0)::BIGINT AS n_items, coalesce(array_to_string(ids, ','), '') AS item_ids FROM d LEFT JOIN every USING (doc_id)"""
