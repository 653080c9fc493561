"""Line dedup by winnowing over line hashes, in DataFrame functions only.

A text is split at line feeds; blank lines (nothing but spaces) are passed over and stay.

1. Winnowing. Of every `min_run` consecutive lines the one with the smallest hash (the rightmost of equals) is chosen; a
   line that several windows choose is one position. Two equal runs of `min_run` lines choose the same line, so every
   repeated run is certain to show a fingerprint in both places.
2. Positions meet by fingerprint. Each is extended both ways, to as many lines on each side as the windows that chose
   it reach: (fingerprint, lines to the left, hash of the lines on both sides). Of the positions that agree in one such
   extension the earliest (smaller doc_id, then earlier line) is the original. A fingerprint with many extensions
   is parted by them before the shuffle's end, so a line that a third of all texts share costs one row per map task and
   extension, and no pair of positions is ever listed.
3. Runs. A chosen position that is not the original of an extension is a repeat of the lines it was extended over;
   overlapping and neighbouring ones fuse into runs of any length, which are deleted. Only originals travel back.

With `long_words` a line of at least that many words is also a window of its own, so a passage held in one line, or a
document of one line, is found wherever it stands; shorter lines count only inside runs. Without it (the default, and
what ORACLE says) only runs of `min_run` lines are found.

Defined results: windows are judged on the input; a null text has no lines and stays null; rows with a null doc_id
keep their text; rows that repeat another's doc_id and text get the same answer; rows with one doc_id and different
texts are documents of their own, ordered by a hash of the text; an empty table gives an empty result; columns of any
other name stay as they are. Very long texts are judged whole, as arrays of lines in one row. Two windows of different
lines count as equal only if two 64-bit hashes collide at once.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import text_key

MIN_RUN = 2
LONG_WORDS = 8


def let(value: Column, then: Callable[[Column], Column]) -> Column:
    """then(value) with value computed once a row. A column that a lambda refers to would be put into the lambda by the
    optimiser and computed once an element."""
    return F.get(F.transform(F.array(value), then), F.lit(0))


def _numbers(size: Column) -> Column:
    return F.when(size > 0, F.sequence(F.lit(0), size - 1)).otherwise(F.array().cast("array<int>"))


def _with_lines(text: Column, then: Callable[[Column, Column], Column]) -> Column:
    """then(lines, numbers of the lines that aren't blank)."""
    lines = F.split(F.coalesce(text, F.lit("")), "\n", -1)
    full = lambda found: F.filter(_numbers(F.size(found)), lambda i: F.trim(F.get(found, i)) != "")
    return let(lines, lambda found: let(full(found), lambda kept: then(found, kept)))


def _long(lines: Column, full: Column, long_words: int) -> Column:
    """Which lines that aren't blank, counted without the blank ones, have at least long_words words."""
    words = lambda i: F.size(F.filter(F.split(F.get(lines, F.get(full, i)), "[ \\t-\\r]+"), lambda word: word != ""))
    return F.filter(_numbers(F.size(full)), lambda i: words(i) >= long_words)


def _positions(hashes: Column, min_run: int) -> Column:
    """Chosen lines: at, mark (the fingerprint) and sides, what each window that chose the line adds around it: how many
    lines to the left (offset) and a hash of the lines on both sides."""
    starts = _numbers(F.size(hashes) - (min_run - 1))

    def pick(i: Column) -> Column:
        window = F.slice(hashes, i + 1, min_run)
        return (i + min_run - F.array_position(F.reverse(window), F.array_min(window))).cast("int")

    def position(picks: Column, p: Column) -> Column:
        chose = F.filter(F.sequence(F.greatest(p - (min_run - 1), F.lit(0)), F.least(p, F.size(picks) - 1)), lambda i: F.get(picks, i) == p)
        around = lambda i: F.xxhash64(F.slice(hashes, i + 1, p - i), F.slice(hashes, p + 2, i + (min_run - 1) - p))
        return F.struct(p.alias("at"), F.get(hashes, p).alias("mark"), F.transform(chose, lambda i: F.struct((p - i).alias("offset"), around(i).alias("around"))).alias("sides"))

    return let(F.transform(starts, pick), lambda picks: F.transform(F.array_distinct(picks), lambda p: position(picks, p)))


def _fingerprints(text: Column, min_run: int, long_words: int | None) -> Column:
    """Chosen positions of a text. A long line on its own has the offset -1 and extends over itself only."""

    def all_of(lines: Column, full: Column) -> Column:
        runs = let(F.transform(full, lambda i: F.xxhash64(F.get(lines, i))), lambda hashes: _positions(hashes, min_run))
        if long_words is None:
            return runs
        line = lambda i: F.get(lines, F.get(full, i))
        alone = lambda i: F.struct(i.alias("at"), F.xxhash64(line(i)).alias("mark"), F.array(F.struct(F.lit(-1).alias("offset"), F.xxhash64(F.lit(1), line(i)).alias("around"))).alias("sides"))
        return F.concat(runs, F.transform(_long(lines, full, long_words), alone))

    return _with_lines(text, all_of)


def _judged(text: Column, first: Column, min_run: int, long_words: int | None) -> Column:
    """n_lines, removed and kept_text, given the windows that stay; first null: all stay."""

    def of(lines: Column, full: Column) -> Column:
        windows = _numbers(F.size(full) - (min_run - 1))
        lines_of = lambda w: F.sequence(w, w + (min_run - 1))
        if long_words is not None:
            windows = F.concat(windows, F.transform(_long(lines, full, long_words), lambda i: -1 - i))
            lines_of = lambda w: F.when(w < 0, F.array(-1 - w)).otherwise(F.sequence(w, w + (min_run - 1)))
        again = F.array_except(windows, F.coalesce(first, windows))
        covered = F.array_distinct(F.flatten(F.transform(again, lines_of)))
        return let(F.transform(covered, lambda k: F.get(full, k)), lambda removed: kept(lines, removed))

    def kept(lines: Column, removed: Column) -> Column:
        stays = F.array_except(_numbers(F.size(lines)), removed)
        text = F.array_join(F.transform(stays, lambda i: F.get(lines, i)), "\n")
        return F.struct(F.size(lines).cast("long").alias("n_lines"), F.sort_array(removed).alias("removed"), text.alias("kept_text"))

    return _with_lines(text, of)


def originals(docs: DataFrame, min_run: int, long_words: int | None = None) -> DataFrame:
    """id, key and first: the windows of each document whose chosen position is the earliest of its extension. A window
    is named by its first line; a long line k on its own by -1 - k."""
    rows = docs.select(F.col("doc_id").cast("long").alias("id"), text_key(F.col("text")).alias("key"), "text").where(F.col("doc_id").isNotNull() & (F.length("text") > 0))
    positions = rows.select("id", "key", F.explode(_fingerprints(F.col("text"), min_run, long_words)).alias("p")).select("id", "key", "p.*")
    extended = positions.select("id", "key", "at", "mark", F.inline("sides"))
    place = F.struct("id", "key", "at")
    earliest = extended.groupBy("mark", "offset", "around").agg(F.min(place).alias("p"))
    window = F.when(F.col("offset") < 0, -1 - F.col("p.at")).otherwise(F.col("p.at") - F.col("offset"))
    return earliest.select("p.id", "p.key", window.alias("window")).groupBy("id", "key").agg(F.collect_list("window").alias("first"))


def removed_runs(docs: DataFrame, min_run: int = MIN_RUN, long_words: int | None = None) -> DataFrame:
    """row (a struct of all columns of docs) and found(n_lines, removed, kept_text)."""
    rows = docs.select(F.struct(*docs.columns).alias("row"), F.col("doc_id").cast("long").alias("id"), text_key(F.col("text")).alias("key"))
    joined = rows.join(originals(docs, min_run, long_words), ["id", "key"], "left")
    first = F.when(F.col("id").isNotNull(), F.coalesce("first", F.array().cast("array<int>")))
    return joined.select("row", _judged(F.col("row.text"), first, min_run, long_words).alias("found"))


def dedup_lines(docs: DataFrame, min_run: int = MIN_RUN, long_words: int | None = None) -> DataFrame:
    """doc_id, n_lines, removed (line numbers from 0, ascending) and kept_text of each row with a doc_id."""
    found = removed_runs(docs.select("doc_id", "text").where(F.col("doc_id").isNotNull()), min_run, long_words)
    lines = F.when(F.length("row.text") > 0, F.col("found.n_lines")).otherwise(0)
    return found.select(F.col("row.doc_id").cast("long").alias("doc_id"), lines.alias("n_lines"), "found.removed", F.when(F.col("row.text").isNotNull(), F.col("found.kept_text")).alias("kept_text"))


def without_repeats(docs: DataFrame, min_run: int = MIN_RUN, long_words: int | None = None) -> DataFrame:
    """docs with its columns, repeated runs taken out of text (n_chars follows); a text of which nothing but blank
    lines is left goes with its row."""
    found = removed_runs(docs, min_run, long_words)
    touched = F.size("found.removed") > 0
    stays = found.where(~touched | (F.trim(F.regexp_replace("found.kept_text", "\n", "")) != ""))
    new = {"text": F.when(touched, F.col("found.kept_text")).otherwise(F.col("row.text"))}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(touched, F.length("found.kept_text")).otherwise(F.col("row.n_chars")).cast(docs.schema["n_chars"].dataType)
    return stays.select(*[new[c].alias(c) if c in new else F.col("row")[c].alias(c) for c in docs.columns])


def digest(found: DataFrame) -> DataFrame:
    return found.select("doc_id", "n_lines", F.size("removed").cast("long").alias("n_removed"), F.sha2(F.coalesce("kept_text", F.lit("")).cast("binary"), 256).alias("kept_sha256"))


ORACLE = f"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS n
  FROM documents WHERE length(text) > 0
), full_lines AS (
  SELECT doc_id, n, line, row_number() OVER (PARTITION BY doc_id ORDER BY n) AS k FROM lines WHERE trim(line) <> ''
), windows AS (
  SELECT doc_id, k, list(line) OVER (PARTITION BY doc_id ORDER BY k ROWS BETWEEN CURRENT ROW AND {MIN_RUN - 1} FOLLOWING) AS run
  FROM full_lines
), judged AS (
  SELECT doc_id, k, row_number() OVER (PARTITION BY run ORDER BY doc_id, k) > 1 AS again FROM windows WHERE len(run) = {MIN_RUN}
), gone AS (
  SELECT DISTINCT f.doc_id, f.n FROM judged j JOIN full_lines f ON f.doc_id = j.doc_id AND f.k BETWEEN j.k AND j.k + {MIN_RUN - 1} WHERE j.again
), kept AS (
  SELECT l.doc_id, string_agg(l.line, chr(10) ORDER BY l.n) AS body
  FROM lines l LEFT JOIN gone g ON g.doc_id = l.doc_id AND g.n = l.n WHERE g.n IS NULL GROUP BY l.doc_id
), counts AS (
  SELECT l.doc_id, count(*) AS n_lines, count(g.n) AS n_removed FROM lines l LEFT JOIN gone g ON g.doc_id = l.doc_id AND g.n = l.n GROUP BY l.doc_id
)
SELECT d.doc_id, coalesce(c.n_lines, 0) AS n_lines, coalesce(c.n_removed, 0) AS n_removed, sha256(coalesce(k.body, '')) AS kept_sha256
FROM documents d LEFT JOIN counts c USING (doc_id) LEFT JOIN kept k USING (doc_id) WHERE d.doc_id IS NOT NULL
"""
