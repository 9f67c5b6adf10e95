"""Secret scans, in DataFrame functions only: fixed patterns, and what corpus-wide ownership frequency adds to them.

Three patterns give the base spans. Beside them, long tokens of any length are candidates: such that mix digits and letters,
or of the base64 alphabet with digits and letters of both cases. The hash of each candidate and of each base span's value is
aggregated over the corpus: in how many distinct repositories and owners it stands. One that several owners share is a
copied example, one that a single owner holds looks live. Live candidates apart from base spans are added to these; base
spans all stay, and ``verdicts`` tells for every span which of the two it is.

A text is cut at each match; a match starts where the pieces and matches before it end, summed in blocks of 256, so a text
with very many matches costs no quadratic time. The corpus aggregate is reduced to distinct (hash, repository, owner)
before it is shuffled, and again per hash, so a token in a third of all rows is as many rows as it has owners.

Edge cases: a null text is empty; null repositories and owners count as one; rows that repeat an id and text get equal spans;
null ids are matched null-safely; extra columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphpart.llm.common import ID, TEXT, durable

#: Kind, pattern, group whose length counts, least length.
PATTERNS = (
    ("assign", r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 1, 6),
    ("access", r"AKIA[A-Z0-9]+", 0, 20),
    ("hex", r"[0-9a-f]{24,}", 0, 24),
)
CANDIDATE = (
    r"(?<![A-Za-z0-9_+/-])(?:(?=[A-Za-z_-]*+[0-9])(?=[0-9_-]*+[A-Za-z])[A-Za-z0-9_-]{20,}+(?![+/=])"
    r"|(?=[a-z0-9_+/-]*+[A-Z])(?=[A-Z0-9_+/-]*+[a-z])(?=[A-Za-z_+/-]*+[0-9])[A-Za-z0-9_+/-]{20,}+={0,2}+)"
)
BLOCK = 256
MOST_BROADCAST = 500_000
SALTS = 32


def _sum(values: Column) -> Column:
    return F.aggregate(values, F.lit(0), lambda a, x: a + x)


def _starts(lengths: Column) -> Column:
    """Exclusive running sums of an array of ints, by blocks."""
    blocks = F.transform(F.sequence(F.lit(0), F.expr("0") + F.floor((F.size(lengths) - 1) / BLOCK).cast("int")), lambda b: _sum(F.slice(lengths, b * BLOCK + 1, F.lit(BLOCK))))
    within = F.transform(lengths, lambda _, i: _sum(F.slice(lengths, F.floor(i / BLOCK).cast("int") * BLOCK + 1, i % BLOCK)))
    before = F.transform(blocks, lambda _, i: _sum(F.slice(blocks, F.lit(1), i)))
    return F.when(F.size(lengths) == 0, F.array().cast("array<int>")).otherwise(F.transform(within, lambda s, i: s + F.element_at(before, F.floor(i / BLOCK).cast("int") + 1)))


def _matches(text: Column, pattern: str, group: int) -> Column:
    """Array of (start, end, length of the group, the group) of a pattern's leftmost, non-overlapping matches."""
    whole = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    inner = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else whole
    gaps = F.split(text, pattern, -1)
    steps = F.transform(whole, lambda m, i: F.char_length(F.element_at(gaps, i + 1)) + F.char_length(m))
    row = F.struct(whole.alias("w"), inner.alias("g"), gaps.alias("p"), steps.alias("s"))
    out = F.transform(F.array(row), lambda r: _located(r))
    found = F.element_at(out, 1)
    return F.when(F.regexp_like(text, F.lit(pattern)), found).otherwise(F.lit(None).cast("array<struct<start:int,end:int,inner:int,word:string>>"))


def _located(r: Column) -> Column:
    starts = _starts(r["s"])
    return F.transform(
        starts,
        lambda at, i: F.struct(
            (at + F.char_length(F.element_at(r["p"], i + 1))).alias("start"),
            (at + F.element_at(r["s"], i + 1)).alias("end"),
            F.char_length(F.element_at(r["g"], i + 1)).alias("inner"),
            F.element_at(r["g"], i + 1).alias("word"),
        ),
    )


SPANS = "array<struct<start:int,rank:int,end:int,kind:string,hash:bigint>>"
JUDGED = "array<struct<start:int,rank:int,end:int,kind:string,verdict:string>>"


def base_and_candidates(docs: DataFrame, repo_col: str, owner_col: str) -> DataFrame:
    """(doc_id, repo, owner, text_key, base, candidates), one scan of the texts, kept in the shared folder. Candidates that
    touch a base span are left out: that span's value stands for them.
    """
    text = F.coalesce(F.col(TEXT), F.lit(""))
    df = docs.select(ID, F.col(repo_col).cast("string").alias("repo"), F.col(owner_col).cast("string").alias("owner"), F.xxhash64(text).alias("text_key"), text.alias("_text"))
    for kind, pattern, group, _ in PATTERNS:
        df = df.withColumn(f"m_{kind}", _matches(F.col("_text"), pattern, group))
    df = df.withColumn("m_owned", _matches(F.col("_text"), CANDIDATE, 0))
    none = F.array().cast("array<struct<start:int,end:int,inner:int,word:string>>")

    def part(rank: int, kind: str, least: int) -> Column:
        kept = F.filter(F.coalesce(F.col(f"m_{kind}"), none), lambda m: m["inner"] >= least)
        return F.transform(kept, lambda m: F.struct(m["start"].alias("start"), F.lit(rank).alias("rank"), m["end"].alias("end"), F.lit(kind).alias("kind"), F.xxhash64(m["word"]).alias("hash")))

    parts = [part(rank, kind, least) for rank, (kind, _, _, least) in enumerate(PATTERNS)]
    df = df.withColumn("base", F.array_sort(F.concat(*parts)).cast(SPANS)).withColumn("found", part(len(PATTERNS), "owned", 0).cast(SPANS))
    apart = F.filter("found", lambda c: ~F.exists("base", lambda b: (b["start"] < c["end"]) & (c["start"] < b["end"])))
    return durable(df.select(ID, "repo", "owner", "text_key", "base", apart.alias("candidates")))


def ownership(found: DataFrame) -> DataFrame:
    """(hash, repos, owners, places) of each candidate and base value: distinct repositories and owners, reduced before each shuffle."""
    one = found.select("repo", "owner", F.explode(F.concat("base", "candidates")).alias("c"))
    by_owner = one.groupBy(F.col("c.hash").alias("hash"), "repo", "owner").agg(F.count(F.lit(1)).alias("places"))
    return by_owner.groupBy("hash").agg(
        F.count_distinct(F.coalesce("repo", F.lit(""))).alias("repos"), F.count_distinct(F.coalesce("owner", F.lit(""))).alias("owners"), F.sum("places").alias("places")
    )


def find_secrets(docs: DataFrame, repo_col: str = ID, owner_col: str = "source", most_owners: int = 1, most_repos: int | None = None) -> DataFrame:
    """(doc_id, n_assign, n_access, n_hex: the patterns' counts; base_sha256; spans: all; n_added; n_copied; verdicts: of all spans).

    Copied are values of over ``most_owners`` owners or, if that is given, over ``most_repos`` repositories.
    """
    found = base_and_candidates(docs, repo_col, owner_col)
    widely = F.col("owners") > most_owners
    if most_repos is not None:
        widely = widely | (F.col("repos") > most_repos)
    copied = durable(ownership(found).where(widely).select("hash", F.lit("copied").alias("verdict")))
    asked = found.where((F.size("base") > 0) | (F.size("candidates") > 0)).select(ID, "text_key", F.explode(F.concat("base", "candidates")).alias("s"))
    asked = asked.select(ID, "text_key", "s", F.col("s.hash").alias("hash"))
    if copied.count() <= MOST_BROADCAST:  # 16 bytes a hash
        told = asked.join(F.broadcast(copied), "hash", "left")
    else:  # a hot hash is dealt over SALTS partitions
        salted = copied.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        told = asked.withColumn("salt", F.pmod(F.xxhash64(ID, "text_key"), F.lit(SALTS)).cast("int")).join(salted, ["hash", "salt"], "left")
    span = F.struct("s.start", "s.rank", "s.end", "s.kind", F.coalesce("verdict", F.lit("live")).alias("verdict"))
    kept = told.where((F.col("s.rank") < len(PATTERNS)) | F.col("verdict").isNull())
    judged = kept.groupBy(ID, "text_key").agg(F.array_sort(F.collect_set(span)).cast(JUDGED).alias("judged"))
    left, right = found.alias("l"), judged.alias("r")
    joined = left.join(right, F.col(f"l.{ID}").eqNullSafe(F.col(f"r.{ID}")) & (F.col("l.text_key") == F.col("r.text_key")), "left")
    base, spans = F.col("l.base"), F.coalesce(F.col("r.judged"), F.array().cast(JUDGED))
    written = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    count = lambda kind: F.size(F.filter(base, lambda s: s["kind"] == kind)).cast("long")
    return joined.select(
        F.col(f"l.{ID}").alias(ID),
        *(count(kind).alias(f"n_{kind}") for kind, *_ in PATTERNS),
        F.sha2(written(base), 256).alias("base_sha256"),
        written(spans).alias("spans"),
        (F.size(spans) - F.size(base)).cast("long").alias("n_added"),
        F.size(F.filter(spans, lambda s: s["verdict"] == "copied")).cast("long").alias("n_copied"),
        F.array_join(F.transform(spans, lambda s: s["verdict"]), ",").alias("verdicts"),
    )
