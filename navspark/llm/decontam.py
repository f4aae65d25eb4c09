"""Benchmark decontamination with a broadcast hash set of test n-grams.

Texts become lower-cased (A-Z) words. A window is 13 consecutive words of a benchmark item;
a shorter item is one window of its own length. Documents are scanned once: word hashes are
combined by doubling into window hashes, which are matched against the hash set of all
benchmark windows. Hits are then verified word by word, and covered words are counted by
merging intervals. Everything is built-in functions. Texts are joined to their hits by a
broadcast of the hits as long as these fit one, which is checked; beyond that by a shuffle.

Defined results: null text has no words; an item without words has no windows; items without
an id hit like others and count together as one item that adds no id to the list; repeated
rows are judged each by its own text; a null doc_id is an ordinary value; empty tables give
no hits; extra columns, whatever their names, are carried by the filters and ignored else.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from navspark.llm.common import apart, az_lower, checked, once, same_row, text_key, whole, written

N = 13  #: words of a window
_SEP = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]"  # ASCII but letters and digits
_WORD = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]"


def words(text: Column) -> Column:
    return F.array_remove(F.split(F.coalesce(text.cast("string"), F.lit("")), _SEP + "+", -1), "")


def _part(c: str, first: int, n: Column) -> Column:
    return F.slice(c, first + 1, F.greatest(n, F.lit(0)))


def with_window_hashes(df: DataFrame, lengths: list[int], word_col: str = "w", fold=F.lower) -> DataFrame:
    """Adds ``n`` (words) and h<L>, the hashes of all windows of L words, for each L.

    h1 hashes words; a window of 2k words is the hash of its two halves; other lengths are
    put together from powers of two. Arrays are always arguments and never captured in a
    lambda, so each is computed once a row.
    """
    df = df.withColumn("n", F.size(word_col)).withColumn("h1", F.transform(word_col, lambda w: F.xxhash64(fold(w))))
    have = {1}

    def join(df: DataFrame, a: int, b: int) -> DataFrame:
        if a + b in have:
            return df
        have.add(a + b)
        n = F.col("n") - (a + b - 1)
        return df.withColumn(f"h{a + b}", F.zip_with(_part(f"h{a}", 0, n), _part(f"h{b}", a, n), lambda x, y: F.xxhash64(x, y)))

    for length in lengths:
        k = 1
        while 2 * k <= length:
            df, k = join(df, k, k), 2 * k
        done = k
        while done < length:
            k = 1 << ((length - done).bit_length() - 1)
            df, done = join(df, done, k), done + k
    return df


def benchmark_windows(bench: DataFrame, n: int = N) -> tuple[DataFrame, list[int]]:
    """(h, len, words, items, nameless) of each distinct window, and the window lengths that occur."""
    items = bench.select("item_id", words(az_lower(F.col("text").cast("string"))).alias("w")).where(F.size("w") > 0)
    items = items.withColumn("len", F.least(F.size("w"), F.lit(n)))
    lengths = sorted(r[0] for r in items.select("len").distinct().collect())  # n values at most
    hashed = with_window_hashes(items, lengths)
    flat = None
    for size in lengths:
        one = hashed.where(F.col("len") == size).select("item_id", "w", "len", F.posexplode(f"h{size}").alias("pos", "h"))
        flat = one if flat is None else flat.unionByName(one)
    if flat is None:
        return None, []
    flat = flat.select("item_id", "len", "h", F.array_join(F.slice("w", F.col("pos") + 1, F.col("len")), " ").alias("words"))
    nameless = F.max(F.col("item_id").isNull().cast("int")).alias("nameless")
    return written(flat.groupBy("h", "len", "words").agg(F.collect_set("item_id").alias("items"), nameless), "windows"), lengths


def covered_words(spans, place=lambda x: x.pos, size=lambda x: x.len) -> Column:
    """Words inside any of the spans, which are sorted by place."""
    return F.aggregate(
        spans,
        F.struct(F.lit(0).alias("end"), F.lit(0).alias("sum")),
        lambda acc, x: F.struct(
            F.greatest(acc.end, place(x) + size(x)).alias("end"),
            (acc["sum"] + F.greatest(F.lit(0), place(x) + size(x) - F.greatest(acc.end, place(x)))).alias("sum"),
        ),
        lambda acc: acc["sum"],
    )


def contamination(docs: DataFrame, bench: DataFrame, n: int = N) -> DataFrame:
    """One row for each row of ``docs``: doc_id, row_key, n_words, spans (array of start and
    length in words, verified), items (sorted array of item ids as strings), n_hit, n_items."""
    docs = docs.select("doc_id", F.col("text").cast("string").alias("text")).withColumn("row_key", text_key())
    windows, lengths = benchmark_windows(bench, n)
    base = docs.select("doc_id", "row_key", "text", words(F.col("text")).alias("w"))
    if not lengths:
        return base.select("doc_id", "row_key", F.size("w").alias("n_words"), F.expr("cast(array() as array<struct<pos:int,len:int>>)").alias("spans"), F.expr("cast(array() as array<string>)").alias("items"), F.lit(0).alias("n_hit"), F.lit(0).alias("n_items"))
    hashes = windows.select("h").distinct()
    hashed = with_window_hashes(base.select("doc_id", "row_key", "w"), lengths)
    found = hashed.select("doc_id", "row_key", "n", F.posexplode(F.concat(*[F.col(f"h{x}") for x in lengths])).alias("at", "h"))
    found = found.join(checked(hashes, 16), "h", "left_semi")
    # The arrays of all lengths were joined end to end: find the length and place again.
    start, place, size = F.lit(0), None, None
    for x in lengths:
        rows = F.greatest(F.col("n") - (x - 1), F.lit(0))
        here = F.col("at") < start + rows
        place = F.when(here, F.col("at") - start) if place is None else place.when(here, F.col("at") - start)
        size = F.when(here, F.lit(x)) if size is None else size.when(here, F.lit(x))
        start = start + rows
    found = found.select("doc_id", "row_key", F.struct(place.cast("int").alias("pos"), size.cast("int").alias("len")).alias("hit"))
    per_doc = written(found.groupBy("doc_id", "row_key").agg(F.collect_set("hit").alias("hits")), "hits")
    b = checked(per_doc, 48, "hits").alias("b")
    met = docs.alias("a").join(b, same_row(docs, per_doc), "inner").select("a.doc_id", "a.row_key", "a.text", "b.hits")
    exact = met.select("doc_id", "row_key", "hits", once(words(az_lower(F.col("text")))).alias("w")).where(F.size("w") > 0)
    exact = exact.select(
        "doc_id", "row_key", F.explode(F.transform("hits", lambda x: F.struct(x.pos.alias("pos"), x.len.alias("len"), F.array_join(F.slice("w", x.pos + 1, x.len), " ").alias("words")))).alias("x")
    ).select("doc_id", "row_key", "x.*")
    sure = exact.join(checked(windows.select("len", "words", "items", "nameless"), 256, "items"), ["len", "words"])
    hit = written(
        sure.groupBy("doc_id", "row_key").agg(
            F.sort_array(F.collect_set(F.struct("pos", "len"))).alias("spans"),
            F.array_distinct(F.flatten(F.collect_set("items"))).alias("items"),
            F.max("nameless").alias("nameless"),
        ),
        "verified",
    )
    covered = covered_words("spans")
    hit = hit.select("doc_id", "row_key", "spans", F.array_sort(F.transform("items", lambda i: i.cast("string"))).alias("items"), covered.alias("n_hit"), (F.size("items") + F.col("nameless")).alias("n_items"))
    h = checked(hit, 64, "spans").alias("h")
    none = F.expr("cast(array() as array<struct<pos:int,len:int>>)")
    return base.alias("a").join(h, same_row(base, hit), "left").select(
        "a.doc_id",
        "a.row_key",
        F.size("a.w").alias("n_words"),
        F.coalesce("h.spans", none).alias("spans"),
        F.coalesce("h.items", F.expr("cast(array() as array<string>)")).alias("items"),
        F.coalesce("h.n_hit", F.lit(0)).alias("n_hit"),
        F.coalesce("h.n_items", F.lit(0)).alias("n_items"),
    )


def contaminated(share: int = 20) -> Column:
    """At least one word in ``share`` is hit."""
    return (F.col("n_hit") > 0) & (share * F.col("n_hit").cast("long") >= F.col("n_words"))


def without_contaminated(docs: DataFrame, bench: DataFrame) -> DataFrame:
    """Drops documents that the contamination rule rejects; all columns stay."""
    bad = written(contamination(docs, bench).where(contaminated()).select("doc_id", "row_key").distinct(), "contaminated")
    keyed = docs.select(*apart(docs))
    return keyed.join(checked(bad, 24), same_row(keyed, bad), "left_anti").select(*whole(docs))


def without_spans(docs: DataFrame, bench: DataFrame) -> DataFrame:
    """Cuts the hit words, each with what follows it up to the next word, out of the texts."""
    hits = written(contamination(docs, bench).where("n_hit > 0").select("doc_id", "row_key", "spans").distinct(), "spans")
    keyed = docs.select(*apart(docs))
    j = keyed.join(checked(hits, 48, "spans"), same_row(keyed, hits), "left").select(keyed.row, keyed.text, "spans")
    j = j.withColumn("pieces", once(F.when(F.col("spans").isNotNull(), F.regexp_extract_all("text", F.lit(f"{_WORD}+{_SEP}*"), 0))))
    gone = F.flatten(F.transform("spans", lambda x: F.sequence(x.pos, x.pos + x.len - 1)))
    keep = F.array_except(F.sequence(F.lit(0), F.size("pieces") - 1), gone)
    rest = F.concat(F.regexp_extract("text", f"^{_SEP}*", 0), F.array_join(F.transform(keep, lambda i: F.get("pieces", i)), ""))
    return j.withColumn("text", F.when(F.col("spans").isNull() | (F.size("pieces") == 0), F.col("text")).otherwise(rest)).select(*whole(docs))


def op10_result(docs: DataFrame, bench: DataFrame) -> DataFrame:
    got = contamination(docs, bench)
    return got.select(
        "doc_id",
        F.col("n_words").cast("long").alias("n_words"),
        F.col("n_hit").cast("long").alias("n_hit"),
        F.col("n_items").cast("long").alias("n_items"),
        F.sha2(F.array_join("items", ","), 256).alias("items_sha256"),
        contaminated().alias("contaminated"),
    )


OP10_SQL = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM documents),
b AS (SELECT item_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x00-\x2F\x3A-\x60\x7B-\x7F]+'), lambda x: x <> '') AS w FROM benchmark),
bl AS (SELECT item_id, w, least(len(w), 13) AS n FROM b WHERE len(w) > 0),
bw AS (SELECT DISTINCT item_id, n, array_to_string(w[i:i + n - 1], ' ') AS win FROM (SELECT item_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM bl)),
ln AS (SELECT DISTINCT n FROM bw),
dw AS (SELECT doc_id, i, n, array_to_string(w[i:i + n - 1], ' ') AS win FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM d CROSS JOIN ln WHERE len(w) >= n)),
hit AS (SELECT dw.doc_id, dw.i, dw.n, bw.item_id FROM dw JOIN bw ON dw.n = bw.n AND dw.win = bw.win),
cov AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM (SELECT DISTINCT doc_id, i, n FROM hit)) GROUP BY doc_id),
it AS (SELECT doc_id, count(*) AS n_items, string_agg(s, ',' ORDER BY s) AS ids FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS s FROM hit) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(d.w) AS BIGINT) AS n_words, CAST(coalesce(cov.n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(it.n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(it.ids, '')) AS items_sha256, coalesce(cov.n_hit, 0) > 0 AND 20 * coalesce(cov.n_hit, 0) >= len(d.w) AS contaminated
FROM d LEFT JOIN cov ON d.doc_id = cov.doc_id LEFT JOIN it ON d.doc_id = it.doc_id
"""
