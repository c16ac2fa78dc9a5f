"""Quality rules by distribution divergence, in DataFrame functions only.

Each text gives two histograms: of character classes, and of common words of its
language. Both are compared with the language's reference, given or the mean histogram
of all its texts that pass the base rules and are long enough, by Jensen-Shannon
distance (base 2, 0 to 1). Texts shorter than a guard are not judged by the
histogram that the guard belongs to.

Defined results: null and empty texts have no words and fail the base rules.
Null languages form a language of their own. A language without a word list, or
without any reference text, is not judged by the missing histogram. Repeated rows
are judged each; ties do not arise. An empty table gives an empty table. Columns
beyond doc_id, text and lang are not read and cannot clash.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from iterspark.llm.common import collect_bounded, parked

# Very frequent function words of four languages.
COMMON_WORDS = {
    "en": ["the", "of", "and", "to", "a", "in", "is", "that", "it", "for", "was", "on", "with", "as", "be", "by"],
    "fr": ["de", "la", "le", "et", "les", "des", "en", "un", "du", "une", "que", "est", "pour", "par", "dans", "pas"],
    "de": ["der", "die", "und", "in", "den", "von", "zu", "das", "sich", "mit", "auf", "für", "des", "ist", "im", "dem"],
    "es": ["de", "la", "que", "el", "en", "y", "los", "se", "las", "del", "un", "por", "con", "no", "una", "para"],
}
CHAR_CLASSES = ["lower", "white", "upper", "digit", "symbol", "mark", "beyond_ascii", "rest"]
_LETTERS = "abcdefghijklmnop"
MOST_LANGUAGES = 10_000


def base_columns(df: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id", "lang")) -> DataFrame:
    """Base counts and raw class counts of each row; carries only `keep` besides."""
    gap = r"[\x20\x09-\x0D]+"
    t = F.coalesce(F.col(text), F.lit(""))
    df = df.select(*keep, t.alias("_t"))
    rest = F.col("_r")
    df = df.select(
        *keep,
        F.filter(F.split("_t", gap), lambda w: w != "").alias("_w"),
        F.filter(F.split("_t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("_l"),
        F.length("_t").alias("_n"),
        F.regexp_replace("_t", r"[a-z\x20\x09-\x0D]+", "").alias("_r"),
    )
    lists = F.create_map(*[x for lang, ws in COMMON_WORDS.items() for x in (F.lit(lang), F.create_map(*[F.lit(y) for w, k in zip(ws, _LETTERS, strict=True) for y in (w, k)]))])
    df = df.select(
        *keep,
        "_w",
        F.transform("_w", lambda w: F.xxhash64(w)).alias("_h"),
        F.length(F.array_join("_w", "")).cast("long").alias("word_chars"),
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        "_n",
        F.length(rest).alias("_rest"),
        F.try_element_at(lists, F.coalesce(F.col("lang"), F.lit(""))).alias("_list"),
        *[(F.length(rest) - F.length(F.regexp_replace(rest, pattern, ""))).alias(name) for name, pattern in (("upper", "[A-Z]+"), ("digit", "[0-9]+"), ("n_symbols", r"[#*$%&|<>]+"), ("mark", r"[.,;:!?'\"()\-]+"), ("beyond_ascii", r"[^\x00-\x7F]+"))],
    )
    runs = F.transform(F.sequence(F.lit(1), F.size("_h") - 4), lambda i: F.xxhash64(F.slice("_h", i, 5)))
    df = df.select(
        *keep,
        F.size("_w").cast("long").alias("n_words"),
        F.when(F.size("_h") >= 5, runs).otherwise(F.array().cast("array<bigint>")).alias("_g"),
        F.when(F.col("_list").isNotNull(), F.array_join(F.transform("_w", lambda w: F.coalesce(F.try_element_at(F.col("_list"), w), F.lit("~"))), "")).alias("_codes"),
        "word_chars",
        "n_dup_lines",
        F.col("n_symbols").cast("long").alias("n_symbols"),
        (F.col("_n") - F.col("word_chars")).alias("white"),
        (F.col("word_chars") - F.col("_rest")).alias("lower"),
        "upper",
        "digit",
        "mark",
        "beyond_ascii",
        (F.col("_rest") - F.col("upper") - F.col("digit") - F.col("n_symbols") - F.col("mark") - F.col("beyond_ascii")).alias("rest"),
    ).withColumn("symbol", F.col("n_symbols"))
    # Only texts with a repeated window pay for the sort.
    sorted_runs = F.sort_array(F.transform("_g", lambda x, i: F.struct(x.alias("x"), i.alias("i"))))
    df = df.withColumn("_s", F.when(F.size(F.array_distinct("_g")) < F.size("_g"), sorted_runs))
    s = F.col("_s")
    twice = F.filter(s, lambda e, i: F.coalesce((i > 0) & (F.get(s, F.greatest(i - 1, F.lit(0)))["x"] == e["x"]), F.lit(False)) | F.coalesce(F.get(s, i + 1)["x"] == e["x"], F.lit(False)))
    df = df.withColumn("_p", F.sort_array(F.transform(twice, lambda e: e["i"])))
    covered = F.aggregate(
        "_p",
        F.struct(F.lit(0).alias("upto"), F.lit(0).alias("n")),
        lambda a, p: F.struct((p + 5).alias("upto"), (a["n"] + p + 5 - F.greatest(a["upto"], p)).alias("n")),
        lambda a: a["n"],
    )
    df = df.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long"))
    hits = [F.length("_codes") - F.length(F.replace(F.col("_codes"), F.lit(k), F.lit(""))) for k in _LETTERS]
    return df.select(
        *keep,
        "n_words",
        "word_chars",
        "n_symbols",
        "n_dup_lines",
        "n_repeat_words",
        F.array(*[F.col(c).cast("int") for c in CHAR_CLASSES]).alias("char_counts"),
        F.when(F.col("_codes").isNotNull(), F.array(*hits, F.length("_codes") - F.length(F.translate("_codes", _LETTERS, "")))).alias("word_hits"),
        ((F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))).alias("base_failed"),
    )


def _shares(counts: Column, total: Column) -> Column:
    return F.transform(counts, lambda x: x / total)


def js_distance(p: Column, q: Column) -> Column:
    """Jensen-Shannon distance of two share arrays of one length; null where one is null."""

    def half(a: Column, b: Column) -> Column:
        terms = F.zip_with(a, b, lambda x, y: F.when(x > 0, x * F.log2(2 * x / (x + y))).otherwise(F.lit(0.0)))
        return F.aggregate(terms, F.lit(0.0), lambda s, x: s + x)

    return F.when(p.isNotNull() & q.isNotNull(), F.sqrt(F.greatest((half(p, q) + half(q, p)) / 2, F.lit(0.0))))


def _with_shares(counted: DataFrame, least_chars: int, least_words: int) -> DataFrame:
    chars = F.aggregate("char_counts", F.lit(0), lambda s, x: s + x)
    # word_hits ends with the number of listed words; the rest of the words make the last bin
    bins = F.concat(F.slice("word_hits", 1, len(_LETTERS)), F.array(F.col("n_words").cast("int") - F.element_at("word_hits", -1)))
    return counted.select(
        "*",
        F.when(chars >= least_chars, _shares(F.col("char_counts"), chars)).alias("_c"),
        F.when(F.col("n_words") >= least_words, _shares(bins, F.col("n_words"))).alias("_v"),
        F.coalesce(F.col("lang"), F.lit("")).alias("_lang"),
    )


def _means(shares: DataFrame) -> DataFrame:
    """Mean histograms by language; null where no text of the language is long enough. Summed as decimals, so that no order shows."""

    def mean(column: str, n: int) -> Column:
        places = [F.avg(F.get(column, F.lit(i)).cast("decimal(20,12)")).cast("double") for i in range(n)]
        return F.when(F.count(column) > 0, F.array(*places))

    sound = shares.filter(~F.col("base_failed"))
    return sound.groupBy(F.col("_lang").alias("lang")).agg(mean("_c", len(CHAR_CLASSES)).alias("char_shares"), mean("_v", len(_LETTERS) + 1).alias("word_shares"))


def language_references(docs: DataFrame, *, text: str = "text", least_chars: int = 200, least_words: int = 100) -> DataFrame:
    """(lang, char_shares, word_shares) of a corpus that is taken as the norm."""
    # written first: the means read each count many times over
    return _means(_with_shares(parked(base_columns(docs, text, ("lang",)), "references"), least_chars, least_words))


def divergence_rules(
    docs: DataFrame,
    *,
    text: str = "text",
    keep: tuple[str, ...] = ("doc_id", "lang"),
    most_char_distance: float = 0.32,
    most_word_distance: float = 0.33,
    most_sum: float = 0.4,
    least_chars: int = 200,
    least_words: int = 100,
    references: DataFrame | None = None,
) -> DataFrame:
    """`keep`, the base counts, base_failed, char_distance, word_distance and kept.

    A distance is null where its guard or a missing reference leaves the text unjudged.
    Each distance has its limit, and their sum another: a text that strays in both is odd.
    `references`: (lang, char_shares, word_shares), such as `language_references` gives of a
    trusted corpus; without them the corpus itself is the norm, which junk would bend.
    """
    shares = _with_shares(parked(base_columns(docs, text, keep), "rules"), least_chars, least_words)
    if references is None:
        references = _means(shares)
    named = references.select(F.coalesce(F.col("lang"), F.lit("")).alias("lang"), "char_shares", "word_shares")
    rows = collect_bounded(named, MOST_LANGUAGES, "languages")
    reference = docs.sparkSession.createDataFrame([tuple(r) for r in rows], "_lang string, _rc array<double>, _rv array<double>")
    judged = shares.join(F.broadcast(reference), "_lang", "left")
    judged = judged.withColumn("char_distance", js_distance(F.col("_c"), F.col("_rc"))).withColumn("word_distance", js_distance(F.col("_v"), F.col("_rv")))
    by_char, by_word = (F.coalesce(F.col(c), F.lit(0.0)) for c in ("char_distance", "word_distance"))
    fine = (by_char <= most_char_distance) & (by_word <= most_word_distance) & (by_char + by_word <= most_sum)
    return judged.select(*keep, "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "char_distance", "word_distance", (~F.col("base_failed") & fine).alias("kept"))


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the rules keep; all columns."""
    rows = docs.select(F.struct("*").alias("_row"), "text", "lang")
    return divergence_rules(rows, keep=("_row", "lang")).filter("kept").select("_row.*")
