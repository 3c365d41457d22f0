"""Lexing as column expressions: comments go, string bodies split on white space, operators go, case is kept."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD = r"([\p{L}\p{N}_]+)"

# Reserved words of the three languages the lexer knows.
JAVA = "abstract assert boolean break byte case catch char class const continue default do double else enum extends final finally float for goto if implements import instanceof int interface long native new package private protected public return short static strictfp super switch synchronized this throw throws transient try void volatile while".split()
C = "auto break case char const continue default do double else enum extern float for goto if inline int long register restrict return short signed sizeof static struct switch typedef union unsigned void volatile while".split()
CSHARP = "abstract as base bool break byte case catch char checked class const continue decimal default delegate do double else enum event explicit extern false finally fixed float for foreach goto if implicit in int interface internal is lock long namespace new null object operator out override params private protected public readonly ref return sbyte sealed short sizeof stackalloc static string struct switch this throw true try typeof uint ulong unchecked unsafe ushort using virtual void volatile while".split()


@dataclass(frozen=True)
class Profile:
    """How one kind of text is lexed: what a comment is, and which words are reserved."""

    name: str
    comment: str | None = None
    keywords: tuple[str, ...] = ()
    code: bool = False


_SLASHES = r"(?s)/\*.*?\*/|//[^\n]*"
PROFILES = {
    "prose": Profile("prose"),
    "java": Profile("java", _SLASHES, tuple(JAVA), True),
    "c": Profile("c", _SLASHES, tuple(C), True),
    "csharp": Profile("csharp", _SLASHES, tuple(CSHARP), True),
    "html": Profile("html", r"(?s)<!--.*?-->|<script\b.*?</script>|<style\b.*?</style>|<[^>]*>"),
}


def strip_comments(text: Column, profile: str = "prose") -> Column:
    comment = PROFILES[profile].comment
    return F.regexp_replace(text, comment, " ") if comment else text


def token_array(text: Column, profile: str = "prose") -> Column:
    """Tokens in reading order; null text gives null."""
    return F.regexp_extract_all(strip_comments(text, profile), F.lit(WORD), F.lit(1))


def tokenize(blocks: DataFrame, profile: str = "prose", text: str = "text") -> DataFrame:
    """(block_id, project_id, token), one row an occurrence. Blocks without tokens have no row."""
    return blocks.select("block_id", "project_id", F.explode(token_array(F.col(text), profile)).alias("token"))


def token_kind(token: Column, profile: str = "prose") -> Column:
    """keyword, literal or identifier."""
    words = PROFILES[profile].keywords
    return F.when(token.isin(*words) if words else F.lit(False), "keyword").when(token.rlike(r"^\p{N}"), "literal").otherwise("identifier")


def normalize_t1(text: Column, profile: str = "prose") -> Column:
    """Layout and comments removed."""
    return F.trim(F.regexp_replace(strip_comments(text, profile), r"\s+", " "))


def normalize_t2(text: Column, profile: str = "prose", mode: str = "blind") -> Column:
    """Names and literals abstracted.

    Prose: case folded, digit runs to NUM, punctuation dropped, words kept. Code, blind: identifiers to ID
    and literals to LIT. Code, consistent: identifiers numbered by first occurrence.
    """
    spec = PROFILES[profile]
    if not spec.code:
        folded = F.regexp_replace(F.lower(strip_comments(text, profile)), r"\p{N}+", "NUM")
        return F.trim(F.regexp_replace(folded, r"[^\p{L}\p{N}_]+", " "))
    tokens = F.regexp_extract_all(strip_comments(text, profile), F.lit(r'("(?:[^"\\]|\\.)*"|[\p{L}_][\p{L}\p{N}_]*|\p{N}[\p{L}\p{N}_.]*|[^\s\p{L}\p{N}_"])'), F.lit(1))
    is_name = lambda t: t.rlike(r"^[\p{L}_]") & ~t.isin(*spec.keywords)
    is_literal = lambda t: t.rlike(r'^[\p{N}"]')
    if mode == "blind":
        return F.array_join(F.transform(tokens, lambda t: F.when(is_name(t), "ID").when(is_literal(t), "LIT").otherwise(t)), " ")
    names = F.array_distinct(F.filter(tokens, is_name))
    numbered = F.transform(tokens, lambda t: F.when(is_name(t), F.concat(F.lit("ID"), F.array_position(names, t).cast("string"))).when(is_literal(t), "LIT").otherwise(t))
    return F.array_join(numbered, " ")


def normalized_lines(text: Column, profile: str = "prose") -> Column:
    """T2-normalised lines, blank ones dropped."""
    return F.filter(F.transform(F.split(strip_comments(text, profile), "\n"), lambda x: normalize_t2(x, profile)), lambda x: x != "")


def count_loc(text: Column, profile: str = "prose") -> Column:
    """Lines that hold more than white space and comments."""
    return F.size(F.filter(F.split(strip_comments(text, profile), "\n"), lambda x: F.trim(F.regexp_replace(x, r"\s+", " ")) != ""))


def bag_of_tokens(tokens: DataFrame) -> DataFrame:
    """(block_id, project_id, token, freq). The map-side half of the aggregate already sees whole blocks."""
    return tokens.groupBy("block_id", "project_id", "token").agg(F.count("*").cast("int").alias("freq"))


def bag_map(bag: DataFrame) -> DataFrame:
    """One map<token, freq> a block."""
    return bag.groupBy("block_id", "project_id").agg(F.map_from_entries(F.collect_list(F.struct("token", "freq"))).alias("bag"))


def elements(bag: DataFrame) -> DataFrame:
    """(block_id, project_id, token, k): the multiset as a set of numbered occurrences."""
    return bag.select("block_id", "project_id", "token", F.explode(F.sequence(F.lit(1), F.col("freq"))).alias("k"))
