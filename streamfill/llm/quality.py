"""Quality rules over words and lines, with line frequencies across documents; DataFrame functions only.

A line that very many documents of a host carry is boilerplate: it is taken out before a document is judged by what
is left. Copies of one document must not make its lines look like that, so documents are counted by a hash of their set
of lines: copies are one document, while near copies, which differ in a line, are several.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle

#: Fixed: characters that part words, and characters counted as symbols.
BLANKS, SYMBOLS = " \t\n\x0b\x0c\r", "#*$%&|<>"
#: Ways the rows of a frequent line are dealt when they meet its verdict.
LINE_SALTS = 32


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(text, r"[\x20\x09-\x0D]+"), "")


def window_hashes(words: Column, width: int) -> Column:
    """A 64-bit hash for every window of so many words; none for shorter texts."""
    hashes = F.transform(F.sequence(F.lit(0), F.size(words) - width), lambda i: F.xxhash64(*(F.get(words, i + k) for k in range(width))))
    return F.when(F.size(words) >= width, hashes).otherwise(F.array().cast("array<bigint>"))


def base_measures(docs: DataFrame, text: str, width: int = 5) -> DataFrame:
    """docs with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and base_failed, of its column `text`."""
    t = F.coalesce(F.col(text), F.lit(""))
    lines = F.filter(F.split(t, "\n"), lambda x: F.length(F.translate(x, BLANKS, "")) > 0)
    df = docs.withColumns({
        "q_words": words_of(t),
        "q_lines": lines,
        "word_chars": F.length(F.translate(t, BLANKS, "")).cast("long"),
        "n_symbols": (F.length(t) - F.length(F.translate(t, SYMBOLS, ""))).cast("long"),
    })
    df = df.withColumns({
        "n_words": F.size("q_words").cast("long"),
        "n_dup_lines": (F.size("q_lines") - F.size(F.array_distinct("q_lines"))).cast("long"),
        "q_windows": window_hashes(F.col("q_words"), width),
    }).drop("q_words")
    repeats = F.size(F.array_distinct("q_windows")) < F.size("q_windows")
    df = df.withColumn("q_sorted", F.when(repeats, F.array_sort(F.transform("q_windows", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))).drop("q_windows")
    same = lambda x, k: F.get("q_sorted", k)["h"].eqNullSafe(x["h"])
    again = F.transform("q_sorted", lambda x, k: F.when(same(x, k + 1) | same(x, k - 1), x["i"]))
    df = df.withColumn("q_starts", F.array_sort(F.filter(again, lambda x: x.isNotNull()))).drop("q_sorted")
    covered = F.aggregate(F.transform("q_starts", lambda x, k: F.least(F.lit(width), F.coalesce(F.get("q_starts", k + 1) - x, F.lit(width)))), F.lit(0).cast("long"), lambda a, b: a + b)
    df = df.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long")).drop("q_starts")
    return df.withColumn("base_failed", (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words")))


def normal_line(line: Column) -> Column:
    return F.array_join(words_of(F.lower(line)), " ")


def judge(docs: DataFrame, *, carry: tuple[str, ...] = (), id_col: str = "doc_id", text_col: str = "text", host_col: str = "source", max_documents: int = 20, least_words: int = 10, least_share: float = 0.2) -> DataFrame:
    """Rows (carry..., doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, left_words, kept).

    A normalised line (lower case, single spaces) is removed on a host where over max_documents different documents
    carry it, however often each is stored. kept is false for base_failed and where removal leaves under least_words
    words or under least_share of the words.
    A null text has no words and fails; a null host is a host of its own; repeated rows are judged each; an empty
    table gives an empty result; other columns are ignored but for those in `carry`.
    """
    measures = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
    rows = docs.select(*(F.col(c).alias(f"c_{c}") for c in carry), F.col(id_col).alias("doc_id"), F.coalesce(F.col(host_col), F.lit("")).alias("q_host"), F.col(text_col).alias("q_text"))
    rows = base_measures(rows, "q_text").drop("q_text")
    per_line = F.transform("q_lines", lambda x: F.struct(F.xxhash64(normal_line(x)).alias("h"), F.size(words_of(x)).alias("n")))
    rows = settle(rows.withColumns({"q_lines": per_line, "q_row": F.monotonically_increasing_id()}))

    seen = rows.select("q_host", F.array_sort(F.array_distinct("q_lines.h")).alias("hs"))
    seen = seen.select("q_host", F.xxhash64("hs").alias("document"), F.explode("hs").alias("h"))
    lines = seen.distinct().groupBy("q_host", "h").agg(F.count("*").alias("documents"))
    frequent = lines.where(F.col("documents") > max_documents).select("q_host", "h")
    frequent = frequent.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(LINE_SALTS - 1))))
    each = rows.select("q_row", "q_host", F.explode("q_lines").alias("x")).select("q_row", "q_host", F.col("x.h").alias("h"), F.col("x.n").alias("n"))
    each = each.withColumn("part", F.pmod(F.xxhash64("q_row"), F.lit(LINE_SALTS)).cast("int"))
    removed = each.join(frequent, ["q_host", "h", "part"]).groupBy("q_row").agg(F.sum("n").alias("removed"))
    left = F.col("n_words") - F.coalesce("removed", F.lit(0))
    kept = ~F.col("base_failed") & (left >= least_words) & (left >= least_share * F.col("n_words"))
    return rows.join(removed, "q_row", "left").select(*(F.col(f"c_{c}").alias(c) for c in carry), *(["doc_id"] if "doc_id" not in carry else []), *measures, left.alias("left_words"), kept.alias("kept"))
