"""Column functions on texts: counts, entropy, checksums, cleaning, similarity. All but rouge_l run on the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from refinery.functions import scores


def let(value: Column, body) -> Column:
    """body of a value that is computed once: a lambda computes what it captures again for each element."""
    return F.element_at(F.transform(F.array(value), body), 1)


def words(text: Column) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), r"\s+"), lambda w: w != "")


def token_count(text: Column) -> Column:
    """White-space tokens; 0 for null."""
    return F.size(words(text)).cast("long")


def task_tokens(count=token_count) -> Column:
    """Tokens that the schema gate bounds, by task type."""
    both = lambda a, b: count(F.concat_ws(" ", a, b))
    longest = F.coalesce(F.array_max(F.transform(F.col("responses"), count)), F.lit(0))
    kind = F.col("task_type")
    return F.when(kind.isin("preference"), both(F.col("instruction"), F.col("chosen"))).when(kind == "grpo", count(F.col("instruction")) + longest).when(kind == "language_modeling", count(F.col("output"))).otherwise(both(F.col("instruction"), F.col("output")))


def chars(text: Column) -> Column:
    return F.filter(F.split(text, ""), lambda c: c != "")


def shannon_entropy(text: Column) -> Column:
    """Bits per character: minus the sum of p log2 p over its characters. Null for null, 0 for empty."""

    def bits(c: Column) -> Column:
        share = lambda x: F.size(F.filter(c, lambda y: y == x)) / F.size(c)
        return F.aggregate(F.array_sort(F.array_distinct(c)), F.lit(0.0), lambda a, x: a - share(x) * F.log2(share(x)))

    return F.when(F.length(text) > 0, let(chars(text), bits)).otherwise(F.when(text.isNotNull(), F.lit(0.0)))


def luhn(digits: Column) -> Column:
    """Whether a string of digits passes the check-digit test of card numbers."""
    d = F.transform(F.filter(F.split(F.reverse(digits), ""), lambda c: c != ""), lambda c, i: F.when(i % 2 == 0, c.cast("int")).otherwise(F.when(c.cast("int") * 2 > 9, c.cast("int") * 2 - 9).otherwise(c.cast("int") * 2)))
    return F.aggregate(d, F.lit(0), lambda a, x: a + x) % 10 == 0


def char_ngrams(text: Column, n: int) -> Column:
    """Distinct character n-grams; a shorter text is one gram."""
    c = chars(text)
    grams = lambda c: F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.size(c) - (n - 1), F.lit(1))), lambda i: F.array_join(F.slice(c, i, n), "")))
    return let(c, grams)


def jaccard(a: Column, b: Column) -> Column:
    """Of two arrays as sets; two empty sets are alike."""
    shared = F.size(F.array_intersect(a, b))
    union = F.size(F.array_distinct(a)) + F.size(F.array_distinct(b)) - shared
    return F.when(union == 0, 1.0).otherwise(shared / union)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def normal_form(text: Column) -> Column:
    """Lower case, white space collapsed and trimmed: the key text of duplicates."""
    # a blank alone is left out of the matches: it would be replaced by itself, at each word
    return F.trim(F.regexp_replace(F.lower(text), r"[\t\n\x0B\f\r]\s*| \s+", " "))


#: Named character references that the native decoder knows.
ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&apos;", "'"), ("&nbsp;", " "), ("&copy;", "©"), ("&middot;", "·"), ("&amp;", "&"))
#: Marks of UTF-8 text that was read as Latin-1.
MOJIBAKE = "[ÂÃ][\u0080-¿]"


def strip_html(text: Column) -> Column:
    text = F.regexp_replace(text, r"(?is)<(script|style)\b.*?</\1\s*>", " ")
    text = F.regexp_replace(text, r"(?s)<!--.*?-->", " ")
    text = F.regexp_replace(text, r"</?[A-Za-z!][^>]*>", " ")
    for name, char in ENTITIES:
        text = F.replace(text, F.lit(name), F.lit(char))
    return text


def repair_mojibake(text: Column) -> Column:
    """Reads the text's Latin-1 bytes as UTF-8, where that lowers the number of marks and loses nothing."""
    again = F.decode(F.encode(text, "ISO-8859-1"), "UTF-8")
    latin = ~text.rlike("[^\u0000-ÿ]")
    fixable = text.rlike(MOJIBAKE) & latin
    # the decoder raises on bytes that aren't UTF-8, so those texts must not reach it
    valid = F.is_valid_utf8(F.encode(F.when(fixable, text), "ISO-8859-1"))
    safe = F.when(fixable & valid, text).otherwise(F.lit(""))
    again = F.decode(F.encode(safe, "ISO-8859-1"), "UTF-8")
    return F.when(fixable & valid & (F.regexp_count(again, F.lit(MOJIBAKE)) < F.regexp_count(text, F.lit(MOJIBAKE))), again).otherwise(text)


def strip_control(text: Column) -> Column:
    return F.regexp_replace(text, r"[\p{Cc}&&[^\t\n\r]]", "")


def collapse_space(text: Column, keep_newlines: bool = True) -> Column:
    blank = "[ \\t\\x0B\\f\\r   -   　]"
    if keep_newlines:
        text = F.regexp_replace(F.regexp_replace(text, f"{blank}+", " "), r" ?\n[ \n]*", "\n")
        return F.regexp_replace(text, r"^[ \n]+|[ \n]+$", "")
    return F.trim(F.regexp_replace(text, f"(?:{blank}|\\n)+", " "))


def sentences(text: Column) -> Column:
    """Trimmed sentences: cut after . ! ? before a blank, and at line ends."""
    return F.filter(F.transform(F.split(F.regexp_replace(F.coalesce(text, F.lit("")), r"([.!?])\s+", "$1\n"), "\n"), lambda s: F.trim(s)), lambda s: s != "")


def word_ngrams(text: Column, n: int) -> Column:
    """Distinct lower-cased word n-grams; a shorter text is one gram."""
    # words are got one by one: a slice copies the whole array each time
    gram = lambda w, i: F.concat_ws(" ", *[F.get(w, i + k) for k in range(n)])
    grams = lambda w: F.when(F.size(w) < n, F.array(F.array_join(w, " "))).otherwise(F.array_distinct(F.transform(F.sequence(F.lit(0), F.greatest(F.size(w) - n, F.lit(0))), lambda i: gram(w, i))))
    return let(words(F.lower(text)), grams)


def rouge_l(hyp: Column, ref: Column) -> Column:
    """F1 of the longest common subsequence of words."""
    return scores.rouge_l(F.lower(F.coalesce(hyp, F.lit(""))), F.lower(F.coalesce(ref, F.lit(""))))


def hash_unit(*parts: Column) -> Column:
    """A number in [0, 1) from the parts: reproducible anywhere (md5), so no rand()."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *[p.cast("string") for p in parts])), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def hash_int(n: int, *parts: Column) -> Column:
    return F.pmod(F.conv(F.substring(F.md5(F.concat_ws("|", *[p.cast("string") for p in parts])), 1, 8), 16, 10).cast("long"), F.lit(n)).cast("int")
