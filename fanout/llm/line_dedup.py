"""Line deduplication by winnowing over line hashes, in DataFrame functions only.

A window is the shortest run of non-blank lines from a given line on that has `min_words` words. Of each window the line with
the smallest hash is selected, the first one of equals; neighbouring windows often share it. Equal windows select the same line,
so any repeated run of `min_words` words or more leaves a selected hash that recurs: the minima are guaranteed fingerprints.
Only they are dealt and joined by their positions. A window whose minimum recurs is a match if its lines (their MD5) recur too.

A match is extended to both sides: every line begins a window, so to the left the run is covered by the windows that begin
there; to the right a window is also taken together with the lines after it, as long as those after its first line have fewer
than `min_words` words. The last of these to lie within a repeated run ends where the run ends. So all maximal repeated runs are
found, whichever earlier copy they continue, without pairs of copies; at most `min_words` ends are taken for each line. Runs that
repeat an earlier one, in one document or across documents, are deleted, and blank lines between two deleted lines with them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import dropped, looked_up, stored, whole

MIN_WORDS = 8


def _lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def _plain(line: Column) -> Column:
    """A line as it is compared: blanks at its ends do not count."""
    return F.btrim(line, F.lit(" \t\x0b\x0c\r"))


def _units(text: Column) -> Column:
    """Array of the non-blank lines: (at, line, h, n): place among all lines from 0, the line, its hash and its words."""
    each = F.transform(
        _lines(text),
        lambda x, i: F.struct(i.alias("at"), _plain(x).alias("line"), F.xxhash64(_plain(x)).alias("h"), F.size(F.split(_plain(x), r"[ \t\x0b\x0c\r]+")).alias("n")),
    )
    return F.filter(each, lambda u: F.length(u["line"]) > 0)


def _once(value: Column, f) -> Column:
    """f(value) with the value bound by a one-element transform, so that it is not computed anew for each use."""
    return F.element_at(F.transform(F.array(value), f), 1)


def _fingerprints(text: Column, min_words: int) -> Column:
    """Array of (fp, at, windows): each selected line with its hash, and the windows that select it as (key, first, last) with their extensions."""

    def run(part: Column) -> Column:
        return F.struct(
            F.unhex(F.md5(F.array_join(F.transform(part, lambda u: u["line"]), "\n"))).alias("key"),
            F.element_at(part, 1)["at"].alias("first"),
            F.element_at(part, -1)["at"].alias("last"),
        )

    def window(at: Column, us: Column) -> Column:
        """(pos, runs) of the window from line number `at` (from 1): its minimum's number and the window with its extensions; null without enough words."""
        near = F.slice(us, at, F.lit(min_words))  # each line has a word at least
        one = F.try_element_at(near, F.lit(1))["n"]
        upto = F.transform(near, lambda u, j: F.struct((j + 1).alias("lines"), F.aggregate(F.slice(near, F.lit(1), j + 1), F.lit(0), lambda s, v: s + v["n"]).alias("n")))
        full = F.filter(upto, lambda x: x["n"] >= min_words)  # the first is the window itself
        ends = F.filter(full, lambda x, i: (i == 0) | (x["n"] - one < min_words))
        low = lambda part: F.array_min(F.transform(part, lambda u, j: F.struct(u["h"].alias("h"), (at + j).alias("pos"))))["pos"]
        alone = (one >= min_words) & (F.coalesce(F.try_element_at(near, F.lit(2))["n"], F.lit(min_words)) >= min_words)
        wide = _once(ends, lambda es: F.when(F.size(es) > 0, F.struct(low(F.slice(near, F.lit(1), es[0]["lines"])).alias("pos"), F.transform(es, lambda x: run(F.slice(near, F.lit(1), x["lines"]))).alias("runs"))))
        return F.when(alone, F.struct(at.alias("pos"), F.array(run(F.slice(near, 1, 1))).alias("runs"))).otherwise(wide)

    def selected(both: Column) -> Column:
        """A line is the minimum of windows that begin at it or fewer than min_words lines before."""
        us, ws = both["us"], both["ws"]

        def of(u: Column, i: Column) -> Column:
            by = F.filter(F.slice(ws, F.greatest(i + 2 - min_words, F.lit(1)), F.least(i + 1, F.lit(min_words))), lambda w: w["pos"] == i + 1)
            return F.struct(u["h"].alias("fp"), u["at"].alias("at"), F.flatten(F.transform(by, lambda w: w["runs"])).alias("windows"))

        return F.filter(F.transform(us, of), lambda x: F.size(x["windows"]) > 0)

    windows = lambda us: F.transform(F.when(F.size(us) > 0, F.sequence(F.lit(1), F.size(us))).otherwise(F.array().cast("array<int>")), lambda at: window(at, us))
    return _once(_units(text), lambda us: _once(F.struct(us.alias("us"), windows(us).alias("ws")), selected))


def _blank_gaps(lines: Column, at: Column) -> Column:
    """Positions between two neighbours in the sorted positions `at` where all lines between them are blank."""
    gaps = F.transform(at, lambda p, k: F.struct((p + 1).alias("a"), (F.get(at, k + 1) - 1).alias("b")))
    gaps = F.filter(gaps, lambda g: (g["a"] <= g["b"]) & ~F.exists(F.slice(lines, g["a"] + 1, F.greatest(g["b"] - g["a"] + 1, F.lit(0))), lambda x: F.length(_plain(x)) > 0))
    return F.flatten(F.transform(gaps, lambda g: F.sequence(g["a"], g["b"])))


def repeated_runs(docs: DataFrame, min_words: int = MIN_WORDS, key: str = "doc_id", text: str = "text") -> DataFrame:
    """documents -> (_run_id, _run_tag, _runs array of (first, last)): the runs of each document that occur earlier.

    Earlier is by (doc_id, hash of the text, line); a null doc_id is first. Rows alike in doc_id and text are one
    document, so they do not repeat each other. Counts are combined before the shuffle, what recurs is stored, and
    rows of a frequent line stay in place in the joins back.
    """
    spark = docs.sparkSession
    rows = docs.select(F.col(key).alias("doc_id"), whole(text).alias("_t"))
    rows = rows.select("doc_id", F.xxhash64("_t").alias("_tag"), F.explode(_fingerprints(F.col("_t"), min_words)).alias("s")).select("doc_id", "_tag", "s.*")
    rows, rows_path = stored(rows)
    spot, place = F.struct("doc_id", "_tag", "at"), F.struct("doc_id", "_tag", "first")
    twice = lambda df, by, what: df.groupBy(by).agg(F.min(what).alias("_origin"), F.max(what).alias("_end"), F.count("*").alias("_n")).filter("_origin != _end")
    recurring, fp_path = stored(twice(rows, "fp", spot).select("fp", "_n"))
    matched = looked_up(rows, recurring, "fp").select("doc_id", "_tag", F.explode("windows").alias("w")).select("doc_id", "_tag", "w.*")
    matched, matched_path = stored(matched)
    dropped(spark, rows_path, fp_path)
    firsts, firsts_path = stored(twice(matched, "key", place).drop("_end"))
    later = looked_up(matched, firsts, "key").filter(place > F.col("_origin"))
    runs, _ = stored(later.groupBy(F.col("doc_id").alias("_run_id"), F.col("_tag").alias("_run_tag")).agg(F.collect_set(F.struct("first", "last")).alias("_runs")))
    dropped(spark, matched_path, firsts_path)
    return runs


def dedup_lines(docs: DataFrame, min_words: int = MIN_WORDS, key: str = "doc_id", text: str = "text") -> DataFrame:
    """documents -> all their columns with the repeated runs cut from the text, and _n_lines, _n_removed (in place of columns of these names).

    The first occurrence of a run stays. Blank lines between two deleted lines go too, others stay. A document of
    repeated lines only keeps its row with an empty text. Null texts stay null with 0 lines; empty texts have one
    empty line. Lines of very long texts are handled in time linear in their number. Repeated rows come out each, alike.
    Rows without a doc_id are cut too, and count as earlier than others. Empty input: no rows. Any other columns pass through.
    """
    names = {c: f"_c{i}" for i, c in enumerate(docs.columns)}
    t, k = names[text], names[key]
    base = docs.toDF(*names.values()).withColumn("_tag", F.xxhash64(whole(t)))
    runs = repeated_runs(docs, min_words, key, text)
    joined = base.join(runs, base[k].eqNullSafe(runs["_run_id"]) & (base["_tag"] == runs["_run_tag"]), "left")
    cut = F.array_distinct(F.flatten(F.transform("_runs", lambda r: F.sequence(r["first"], r["last"]))))
    cut = _once(F.struct(_lines(F.col(t)).alias("ls"), F.array_sort(cut).alias("at")), lambda b: F.concat(b["at"], _blank_gaps(b["ls"], b["at"])))
    n, same = F.size(_lines(F.col(t))), F.col("_runs").isNull() | F.col(t).isNull()
    stay = F.array_except(F.sequence(F.lit(0), n - 1), cut)
    left = _once(_lines(F.col(t)), lambda ls: F.array_join(F.transform(stay, lambda p: F.get(ls, p)), "\n"))
    out = {c: F.when(same, F.col(t)).otherwise(left) if c == text else F.col(x) for c, x in names.items()}
    out |= {"_n_lines": F.when(F.col(t).isNull(), 0).otherwise(n), "_n_removed": F.when(same, 0).otherwise(F.size(cut))}
    return joined.select(*(v.alias(c) for c, v in out.items()))
