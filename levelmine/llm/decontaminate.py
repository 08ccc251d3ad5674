"""Benchmark decontamination: which words of a document lie in a window of a benchmark item. DataFrame functions only.

A prefix-filtered join. A window's words are ordered by their rarity in all documents; for exact containment the prefix
that must be shared is the rarest word alone, so only document words that are some window's rarest word are joined.
The word's place in the window gives the only start the match can have (positional bound), the document's length ends
it (length bound), and the words from there on are compared with the window's (exact verification).

The windows are broadcast while they are at most `broadcast_windows`; beyond, the join is a shuffled one in which each
candidate carries the few words around it.

Defined results. Null text: no words. An item without words, or with a null item_id, is none. Rows that repeat doc_id
and text get the same result each. Equal item_ids count as one item. Empty tables give no rows, or rows without hits.
A long text's words are one row's array; its windows are looked up word by word.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WINDOW = 10
BROADCAST_WINDOWS = 500_000


def words(text: Column) -> Column:
    """A-Z lowered; runs of a-z, 0-9 and all beyond ASCII."""
    text = F.coalesce(text.cast("string"), F.lit(""))
    ascii_only = F.octet_length(text) == F.char_length(text)
    lowered = F.when(ascii_only, F.lower(text)).otherwise(F.translate(text, string.ascii_uppercase, string.ascii_lowercase))
    return F.array_remove(F.split(lowered, r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"), "")


def item_windows(items: DataFrame, window: int = WINDOW) -> DataFrame:
    """(gram, item_ids): the distinct windows and the items that have them."""
    said = items.filter("item_id is not null").select("item_id", words(F.col("text")).alias("w")).filter(F.size("w") > 0)
    each = said.select("item_id", "w", F.explode(F.sequence(F.lit(1), F.greatest(F.size("w") - window + 1, F.lit(1)))).alias("s"))
    return each.select("item_id", F.slice("w", F.col("s"), window).alias("gram")).groupBy("gram").agg(F.collect_set("item_id").alias("item_ids"))


def _by_rarest(grams: DataFrame, docs: DataFrame, small: bool) -> DataFrame:
    """Adds to each window its rarest word and that word's first place."""
    hint = F.broadcast if small else lambda x: x
    vocabulary = grams.select(F.explode("gram").alias("word")).distinct()
    seen = docs.select(F.explode("w").alias("word")).join(hint(vocabulary), "word", "left_semi").groupBy("word").agg(F.count("*").alias("n"))
    placed = grams.select("gram", F.posexplode("gram").alias("place", "word")).join(hint(seen), "word", "left")
    rank = F.struct(F.coalesce("n", F.lit(0)).alias("n"), "word", "place")
    prefix = placed.groupBy("gram").agg(F.min(rank).alias("r")).filter("r.n > 0")  # a word that no document has: no match
    return prefix.join(grams, "gram").select("gram", "item_ids", F.col("r.word").alias("prefix"), F.col("r.place").alias("place"))


def matches(docs: DataFrame, grams: DataFrame, small: bool, window: int = WINDOW) -> DataFrame:
    """docs: key columns k_*, w. -> key columns, start, size, item_ids of every verified occurrence."""
    keys = [c for c in docs.columns if c != "w"]
    prefixed = _by_rarest(grams, docs, small)
    if small:
        at = docs.select(*keys, "w", F.posexplode("w").alias("pos", "word")).join(F.broadcast(prefixed), F.col("word") == F.col("prefix"))
        here, start = F.col("w"), F.col("pos") - F.col("place")
        inner = start
    else:
        before = F.least(F.col("pos"), F.lit(window - 1))
        at = docs.select(*keys, "w", F.posexplode("w").alias("pos", "word"))
        at = at.join(prefixed.select(F.col("prefix").alias("word")).distinct(), "word", "left_semi")
        at = at.select(*keys, "word", "pos", before.alias("before"), F.slice("w", F.col("pos") - before + 1, 2 * window - 1).alias("w"))
        at = at.join(prefixed, F.col("word") == F.col("prefix"))
        here, start = F.col("w"), F.col("pos") - F.col("place")
        inner = F.col("before") - F.col("place")
    fits = (inner >= 0) & (inner + F.size("gram") <= F.size(here))
    same = F.when(fits, F.slice(here, inner + 1, F.size("gram")) == F.col("gram")).otherwise(False)
    return at.filter(same).select(*keys, start.alias("start"), F.size("gram").alias("size"), "item_ids")


def _covered(spans: Column) -> Column:
    """Number of places that sorted (start, size) spans cover."""
    none = F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("n"))

    def add(acc: Column, s: Column) -> Column:
        end = s["start"] + s["size"]
        return F.struct(F.greatest(acc["end"], end).alias("end"), (acc["n"] + F.greatest(end - F.greatest(acc["end"], s["start"]), F.lit(0))).cast("long").alias("n"))

    return F.aggregate(spans, none, add, lambda acc: acc["n"])


def _found(docs: DataFrame, items: DataFrame, window: int, broadcast_windows: int) -> tuple[DataFrame, DataFrame]:
    """The documents' keys and words; keys and verified occurrences."""
    grams = item_windows(items, window)
    small = grams.limit(broadcast_windows + 1).count() <= broadcast_windows
    keyed = docs.select(F.col("doc_id").alias("k_doc"), text_key().alias("k_text"), words(F.col("text")).alias("w"))
    return keyed, matches(keyed, grams, small, window)


def text_key() -> Column:
    return F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit("")))


def contaminated(docs: DataFrame, items: DataFrame, window: int = WINDOW, broadcast_windows: int = BROADCAST_WINDOWS) -> DataFrame:
    """(k_doc, k_text): the keys of the documents with a hit."""
    return _found(docs, items, window, broadcast_windows)[1].select("k_doc", "k_text").distinct()


def contamination(docs: DataFrame, items: DataFrame, window: int = WINDOW, broadcast_windows: int = BROADCAST_WINDOWS) -> DataFrame:
    """doc_id, text_key (hash of the text), n_words, n_hit, n_items, items_sha256, contaminated; one row per row of docs."""
    keyed, occurrences = _found(docs, items, window, broadcast_windows)
    found = occurrences.groupBy("k_doc", "k_text").agg(
        F.sort_array(F.collect_set(F.struct("start", "size"))).alias("spans"),
        F.array_distinct(F.flatten(F.collect_set("item_ids"))).alias("ids"),
    )
    names = F.sort_array(F.transform("ids", lambda i: i.cast("string")))
    found = found.select(F.col("k_doc").alias("f_doc"), F.col("k_text").alias("f_text"), _covered(F.col("spans")).alias("hit"), F.size("ids").cast("long").alias("items"), F.array_join(names, ",").alias("names"))
    counted = keyed.select("k_doc", "k_text", F.size("w").cast("long").alias("n_words"))
    both = counted.join(found, F.col("k_doc").eqNullSafe(F.col("f_doc")) & (F.col("k_text") == F.col("f_text")), "left")
    return both.select(
        F.col("k_doc").alias("doc_id"), F.col("k_text").alias("text_key"), "n_words",
        F.coalesce("hit", F.lit(0).cast("long")).alias("n_hit"),
        F.coalesce("items", F.lit(0).cast("long")).alias("n_items"),
        F.sha2(F.coalesce("names", F.lit("")), 256).alias("items_sha256"),
        (F.coalesce("hit", F.lit(0)) > 0).alias("contaminated"),
    )


_WORDS_SQL = f"regexp_extract_all(translate(coalesce(text, ''), '{string.ascii_uppercase}', '{string.ascii_lowercase}'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+')"

ORACLE = f"""
WITH d AS (SELECT doc_id, {_WORDS_SQL} AS w FROM documents),
i AS (SELECT item_id, {_WORDS_SQL} AS w FROM benchmark WHERE item_id IS NOT NULL),
iw AS (SELECT item_id, least(len(w), 10) AS n, list_slice(w, s, s + least(len(w), 10) - 1) AS g
       FROM (SELECT item_id, w, unnest(range(1, greatest(len(w) - 10, 0) + 2)) AS s FROM i WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT n FROM iw),
dw AS (SELECT doc_id, n, s, list_slice(w, s, s + n - 1) AS g
       FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS s FROM d, sizes)),
hits AS (SELECT DISTINCT doc_id, item_id, s, n FROM dw JOIN iw USING (n, g)),
places AS (SELECT doc_id, count(DISTINCT p) AS hit FROM (SELECT doc_id, unnest(range(s, s + n)) AS p FROM hits) GROUP BY doc_id),
named AS (SELECT doc_id, count(*) AS items, string_agg(CAST(item_id AS VARCHAR), ',' ORDER BY CAST(item_id AS VARCHAR)) AS names
          FROM (SELECT DISTINCT doc_id, item_id FROM hits) GROUP BY doc_id)
SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(hit, 0) AS BIGINT) AS n_hit,
       CAST(coalesce(items, 0) AS BIGINT) AS n_items, sha256(coalesce(names, '')) AS items_sha256, coalesce(hit, 0) > 0 AS contaminated
FROM d LEFT JOIN places USING (doc_id) LEFT JOIN named USING (doc_id)
"""
