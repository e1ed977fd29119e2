"""Cleaning, tokens with character spans, and the two versions of a text.

Offsets count code points and are half-open. Clean coordinates are primary: a clean
text is its words joined by single spaces, so a word's begin is the summed length of
the words before it plus one for each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NOT_LETTERS = r"[^\p{L}]+"

#: Patterns of what alignment must not see, by kind.
KINDS = {
    "citation": r"\[[0-9]+(?:[,;\x20-][0-9\x20]+)*\]|\([A-Z]\p{L}+(?: et al\.)?,? [12][0-9]{3}[a-z]?\)",
    "number": r"[0-9]+(?:[.,][0-9]+)*",
    "contact": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+|https?://[^\x20\n]+|[0-9]{1,3}(?:\.[0-9]{1,3}){3}",
    "junk": r"[#*$%&|<>]{2,}",
    "table": r"(?m)^[^\n]*(?:\|[^\n]*\||\t[^\n]*\t)[^\n]*$",
    "bibliography": r"(?is)\n(?:references|bibliography|literatur|références|referencias)\x20*\n.*$",
}


def clean(text: Column) -> Column:
    """Lower-cased letters, every other run one space."""
    return F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), NOT_LETTERS, " "))


def strip_spans(text: Column, kinds: list[str]) -> Column:
    """The text with each span of the named kinds replaced by one space."""
    for kind in kinds:
        text = F.regexp_replace(text, KINDS[kind], " ")
    return text


def words(clean_text: Column) -> Column:
    """Words of a clean text; none for an empty one."""
    return F.when(F.length(clean_text) > 0, F.split(clean_text, " ")).otherwise(F.array().cast("array<string>"))


def let(value: Column, body) -> Column:
    """Evaluate ``value`` once a row for ``body``; the optimiser may otherwise copy it into a lambda."""
    return F.transform(F.array(value), body)[0]


def begins(ws: Column, chunk: int = 8, levels: int = 1) -> Column:
    """Begin of each word in the clean text, row-local.

    Prefix sums by a tree: chunks of a few lengths are summed outright, their totals in the same way a level up. What is
    left at the top, one total for ``chunk ** levels`` words, is folded; a fold that appends copies what it has, and is
    slow for each element.
    """

    def fold(lengths: Column, start: Column) -> Column:
        zero = F.struct(F.array().cast("array<int>").alias("xs"), start.cast("int").alias("at"))
        step = lambda acc, n: F.struct(F.concat(acc["xs"], F.array(acc["at"])).alias("xs"), (acc["at"] + n).cast("int").alias("at"))
        return F.aggregate(lengths, zero, step, lambda acc: acc["xs"])

    def parts(lengths: Column, size: int) -> Column:
        return F.transform(F.sequence(F.lit(0), ((F.size(lengths) - 1) / size).cast("int")), lambda c: F.slice(lengths, c * size + 1, size))

    def totals(ps: Column) -> Column:
        return F.transform(ps, lambda p: F.aggregate(p, F.lit(0), lambda a, n: a + n))

    def outright(p: Column, start: Column) -> Column:
        sums = [start]
        for k in range(chunk - 1):
            sums.append(sums[-1] + F.get(p, F.lit(k)))
        return F.slice(F.array(*sums), F.lit(1), F.size(p))

    def summed(lengths: Column, level: int) -> Column:
        if level:
            return let(parts(lengths, chunk), lambda ps: F.flatten(F.zip_with(ps, let(totals(ps), lambda ts: summed(ts, level - 1)), outright)))
        return let(parts(lengths, 64), lambda ps: F.flatten(F.zip_with(ps, fold(totals(ps), F.lit(0)), fold)))

    lengths = F.transform(ws, lambda w: F.length(w) + 1)
    return F.when(F.size(ws) > 0, let(lengths, lambda ns: summed(ns, levels))).otherwise(F.array().cast("array<int>"))


def blanks_only(text: Column) -> Column:
    """Lower-cased text without any cleaning: runs of white space become one space."""
    return F.trim(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"[\x20\x09-\x0D]+", " "))


def worded(docs: DataFrame, key: str = "doc_id", text: str = "text", letters: bool = True) -> DataFrame:
    """``doc_id, words, begins``: the form from which passages and grams are cut; the text is read here only."""
    rows = docs.select(F.col(key).alias("doc_id"), words((clean if letters else blanks_only)(F.col(text))).alias("words"))
    return rows.select("doc_id", "words", begins(F.col("words")).alias("begins"))


def tokens(docs: DataFrame) -> DataFrame:
    """``doc_id, pos, word, begin, end`` in clean coordinates."""
    rows = worded(docs)
    rows = rows.select("doc_id", F.posexplode(F.arrays_zip("words", "begins")).alias("pos", "t"))
    return rows.select("doc_id", "pos", F.col("t.words").alias("word"), F.col("t.begins").alias("begin"), (F.col("t.begins") + F.length("t.words")).alias("end"))


def two_versions(docs: DataFrame) -> DataFrame:
    """Full text, clean text, and for each clean word the place where it begins in the full text.

    Every removed character is masked by a space, which keeps length and so offsets. Letters whose lower case has
    another length would break this; they are masked by themselves, not lowered, as only the place counts.
    """
    masked = F.regexp_replace("text", r"[^\p{L}]", " ")
    pieces = F.split(masked, " ")
    starts = F.arrays_zip(pieces.alias("w"), begins(pieces).alias("b"))
    places = F.transform(F.filter(starts, lambda t: F.length(t["w"]) > 0), lambda t: t["b"])
    return docs.select("doc_id", F.col("text").alias("full_text"), clean(F.col("text")).alias("clean_text"), places.alias("clean_to_full"))


def length_gate(docs: DataFrame, lo: int = 1000, hi: int = 60_000) -> DataFrame:
    """Documents of lo to hi space-separated words. A text of w words has at least 2w - 1 characters: that bound reaches the scan."""
    n = F.size(F.filter(F.split("text", r"\x20+"), lambda w: F.length(w) > 0))
    return docs.where(F.length("text") >= 2 * lo - 1).where(n.between(lo, hi))


def html_main_text(pages: DataFrame) -> DataFrame:
    """``page_id, url, title, body``: markup, scripts, styles, navigation, advertisements and comments dropped."""
    html = F.regexp_replace("html", r"(?is)<script.*?</script>|<style.*?</style>|<nav.*?</nav>|<!--.*?-->|<head.*?</head>", " ")
    html = F.regexp_replace(html, r'(?is)<div class="ad">.*?</div>', " ")
    html = F.regexp_replace(html, r"(?is)<[^>]*>", " ")
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        html = F.replace(html, F.lit(name), F.lit(char))
    title = F.regexp_extract("html", r"(?is)<title>(.*?)</title>", 1)
    return pages.select("page_id", "url", F.trim(title).alias("title"), F.trim(F.regexp_replace(html, r"[\x20\n\r\t]+", " ")).alias("body"))
