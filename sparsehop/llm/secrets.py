"""Secret scan with corpus-wide ownership frequency, on DataFrame functions alone.

Spans come from Spark's regular expressions: the pieces between the matches and
the matches themselves, alternately, give every match's place in code points.
Kinds assign, access and hex are the base; issued (tokens with a published
issuer prefix) and pem (private keys, with their body where it stands) are the
method's own.

Each candidate value is hashed and counted over the whole corpus by distinct
repositories and owners. An owner is who publishes (``source``), a repository a
collection of theirs (``source`` and ``lang`` together), unless the caller names
the columns. A value that several owners hold in several repositories is a
copied example; one that a single owner holds, in however many repositories, and
that looks random, is live-looking; what remains is unclear.

Null and empty texts have no spans. Spans that start at one place are listed by
kind, as KINDS orders them. A repeated row counts its spans again, but
repositories and owners are counted distinctly, so it moves no verdict. A null
repository or owner counts as none, and a value that only such rows hold has a
single owner at most.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

# The patterns of the kinds, in the order in which ties are listed.
KINDS = {
    "assign": r"(?:[Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])[\"']?\x20*[:=]\x20*[\"']?[A-Za-z0-9+/_.=-]+",
    "access": r"AKIA[A-Z0-9]{16,}",
    "hex": r"[0-9a-f]{24,}",
    "issued": r"(?:gh[pousr]_[A-Za-z0-9]{36}|xox[abprs]-[A-Za-z0-9-]{20,}|sk_live_[A-Za-z0-9]{24,}|AIza[A-Za-z0-9_-]{35})",
    "pem": r"-----BEGIN [A-Z ]{0,24}PRIVATE KEY-----(?:[A-Za-z0-9+/=\x20\n\r]*-----END [A-Z ]{0,24}PRIVATE KEY-----)?",
}
BASE = ("assign", "access", "hex")
#: Least length of an assigned value, of distinct repositories or owners of a copied example, and of random-looking bits a character.
LEAST_ASSIGNED, COPIED_REPOSITORIES, COPIED_OWNERS, LEAST_DISTINCT = 6, 3, 2, 8
#: Matches of a text that are walked through together.
CHUNK = 64
VALUE_OF_ASSIGN = r"^[A-Za-z_]+[\"']?\x20*[:=]\x20*[\"']?"
SPAN = "array<struct<start:bigint,rank:int,kind:string,end:bigint,value:string>>"


def _let(value: Column, use) -> Column:
    """``use`` of a value that is computed once."""
    return F.element_at(F.transform(F.array(value), use), 1)


def kind_spans(text: Column, kind: str) -> Column:
    """Leftmost matches of one kind that do not overlap, with their places.

    A list that grows by one is copied at every step, so matches are walked in
    chunks: chunk starts first, then the matches of each chunk from its start.
    """
    pattern = F.lit(f"({KINDS[kind]})")
    found = F.regexp_extract_all(text, pattern, F.lit(1))
    pieces = F.split(text, KINDS[kind], -1)
    rank = [*KINDS].index(kind)
    nothing = F.array().cast(SPAN)
    starts = F.array(F.lit(0).cast("long"))

    def width(pair):
        return (F.char_length(pair["piece"]) + F.char_length(pair["hit"])).cast("long")

    def step(state, pair):
        start = state["at"] + F.char_length(pair["piece"])
        end = start + F.char_length(pair["hit"])
        value = F.regexp_replace(pair["hit"], VALUE_OF_ASSIGN, "") if kind == "assign" else pair["hit"]
        one = F.struct(start.cast("long").alias("start"), F.lit(rank).alias("rank"), F.lit(kind).alias("kind"), end.cast("long").alias("end"), value.alias("value"))
        return F.struct(end.cast("long").alias("at"), F.concat(state["out"], F.array(one)).alias("out"))

    def chunked(pairs):
        parts = F.transform(F.sequence(F.lit(0), F.floor((F.size(pairs) - 1) / CHUNK).cast("int")), lambda k: F.slice(pairs, k * CHUNK + 1, F.lit(CHUNK)))
        return _let(parts, walked)

    def walked(parts):
        sizes = F.transform(parts, lambda part: F.aggregate(part, F.lit(0).cast("long"), lambda n, pair: n + width(pair)))
        from_ = F.aggregate(sizes, starts, lambda s, n: F.concat(s, F.array(F.element_at(s, -1) + n)))
        of = lambda part, at: F.aggregate(part, F.struct(at.alias("at"), nothing.alias("out")), step, lambda s: s["out"])
        each = F.filter(F.zip_with(parts, from_, lambda part, at: F.struct(part.alias("part"), at.alias("at"))), lambda x: x["part"].isNotNull())
        return F.flatten(F.transform(each, lambda x: of(x["part"], x["at"])))

    def spans(both):
        pairs = F.filter(F.zip_with(both["pieces"], both["found"], lambda p, h: F.struct(p.alias("piece"), h.alias("hit"))), lambda x: x["hit"].isNotNull())
        return F.when(F.size(both["found"]) > 0, _let(pairs, chunked)).otherwise(nothing)

    out = _let(F.struct(pieces.alias("pieces"), found.alias("found")), spans)
    return F.filter(out, lambda x: F.char_length(x["value"]) >= LEAST_ASSIGNED) if kind == "assign" else out


def secret_spans(docs: DataFrame) -> DataFrame:
    """``docs`` with ``spans``: all matches by start, then kind, then end."""
    text = common.text_of()
    return docs.withColumn("spans", F.array_sort(F.concat(*[kind_spans(text, k) for k in KINDS])))


def ownership(spans: DataFrame, repository: Column, owner: Column) -> DataFrame:
    """Each candidate value's hash with its places, distinct repositories and owners over the whole corpus.

    Pairs of hash and repository (and owner) are made distinct first, so a value
    that a third of all rows hold reaches the final count as a few rows.
    """
    one = spans.select(F.explode("spans").alias("s"), repository.cast("string").alias("repository"), owner.cast("string").alias("owner"))
    keyed = one.select(F.sha2("s.value", 256).alias("hash"), "repository", "owner", _random_looking(F.col("s.value")).alias("random_looking"))
    pairs = keyed.groupBy("hash", "repository", "owner", "random_looking").agg(F.count("*").alias("n"))
    # counted in two steps, distinct pairs first: no list of a value's holders is ever formed
    return pairs.groupBy("hash").agg(
        F.sum("n").alias("n_places"),
        F.count_distinct("repository").alias("n_repositories"),
        F.count_distinct("owner").alias("n_owners"),
        F.max("random_looking").alias("random_looking"),
    )


def _random_looking(value: Column) -> Column:
    """Digits and letters mixed, and at least LEAST_DISTINCT different characters."""
    return value.rlike("[0-9]") & value.rlike("[A-Za-z]") & (F.size(F.array_distinct(F.split(value, ""))) >= LEAST_DISTINCT)


def verdict() -> Column:
    copied = (F.col("n_owners") >= COPIED_OWNERS) & (F.col("n_repositories") >= COPIED_REPOSITORIES)
    own = (F.col("n_owners") <= 1) & F.col("random_looking")
    return F.when(copied, F.lit("example")).when(own, F.lit("live")).otherwise(F.lit("unclear"))


REPOSITORY, OWNER = ("source", "lang"), "source"


def _named(columns: tuple[str, ...]) -> Column:
    """Columns as one name; a null among them gives none."""
    return F.concat(*[x for c in columns for x in (F.lit("/"), F.col(c).cast("string"))])


def secret_candidates(docs: DataFrame, repository: tuple[str, ...] = REPOSITORY, owner: str = OWNER) -> DataFrame:
    """One row for each candidate value of the corpus: hash, counts and verdict. Values themselves are not returned."""
    found = secret_spans(docs)
    return ownership(found, _named(repository), F.col(owner)).withColumn("verdict", verdict())


def scan_secrets(docs: DataFrame, repository: tuple[str, ...] = REPOSITORY, owner: str = OWNER) -> DataFrame:
    """doc_id, spans, and how many of them are copied examples, live-looking or unclear.

    Rows without candidates skip the shuffle; those with them meet the counts by
    hash and come together again by doc_id and the digest of their spans. A value
    that more than a two-thousandth of all spans hold is spread over salts first.
    """
    flat = F.transform("spans", lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"], s["value"]))
    found = common.persist_shared(secret_spans(docs.select("doc_id", "text", *dict.fromkeys([*repository, owner]))).drop("text").withColumn("row", F.xxhash64(F.concat_ws(",", flat))))
    counts = ownership(found, _named(repository), F.col(owner)).withColumn("verdict", verdict())
    rows = found.filter(F.size("spans") > 0).select("doc_id", "row", "spans").dropDuplicates(["doc_id", "row"])
    each = rows.select("doc_id", "row", F.explode("spans").alias("s")).select("doc_id", "row", F.sha2("s.value", 256).alias("hash"))
    counts = common.persist_shared(counts.select("hash", "n_places", "verdict"))
    hot = common.hot_keys(counts, ["hash"], "n_places")
    spread, verdicts = common.salted(each, ["hash"], hot, F.struct("doc_id", "row")), common.repeated_for_salts(counts.select("hash", "verdict"), ["hash"], hot)
    judged = spread.join(verdicts, ["hash", "salt"]).groupBy("doc_id", "row").agg(*[F.count_if(F.col("verdict") == v).alias(f"n_{v}") for v in ("live", "example", "unclear")])
    nought = {f"n_{v}": F.coalesce(F.col(f"n_{v}"), F.lit(0)) for v in ("live", "example", "unclear")}
    both = found.select("doc_id", "row", "spans").alias("f").join(judged.alias("j"), F.col("f.doc_id").eqNullSafe(F.col("j.doc_id")) & (F.col("f.row") == F.col("j.row")), "left")
    return both.select("f.doc_id", "spans", "n_live", "n_example", "n_unclear").withColumns(nought)


def _listed(spans: Column) -> Column:
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))))


def _of_kind(kind: str):
    return lambda s: s["kind"] == kind


def query(spark, sf_dir: str) -> DataFrame:
    found = scan_secrets(common.load(spark, sf_dir, "documents"))
    counted = [F.size(F.filter("spans", _of_kind(k))).cast("long").alias(f"n_{k}") for k in BASE]
    base = F.filter("spans", lambda s: s["kind"].isin(*BASE))
    return found.select("doc_id", *counted, F.sha2(_listed(base), 256).alias("base_sha256"), _listed(F.col("spans")).alias("spans"), "n_live", "n_example", "n_unclear")


def _oracle() -> str:
    part = []
    for rank, (kind, pattern) in enumerate(KINDS.items()):
        quoted = pattern.replace("'", "''")
        value = f"regexp_replace(m, '{VALUE_OF_ASSIGN.replace(chr(39), chr(39) * 2)}', '')" if kind == "assign" else "m"
        keep = f"WHERE length(value) >= {LEAST_ASSIGNED}" if kind == "assign" else ""
        part.append(f"""SELECT doc_id, source, lang, {rank} rank, '{kind}' kind, s, s + length(m) e, value FROM (
            SELECT doc_id, source, lang, m, {value} AS value, list_sum(list_transform(p[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(h[1:i - 1], lambda x: length(x))), 0) s FROM (
              SELECT *, unnest(h) m, unnest(range(1, len(h) + 1)) i FROM (
                SELECT doc_id, source, lang, regexp_extract_all(t, '{quoted}') h, string_split_regex(t, '{quoted}') p FROM d))) {keep}""")
    return f"""WITH d AS (SELECT doc_id, source, lang, coalesce(text, '') t FROM documents), a AS ({' UNION ALL '.join(part)}),
o AS (SELECT value, count(DISTINCT '/' || source || '/' || lang) r, count(DISTINCT source) w,
        max(regexp_matches(value, '[0-9]') AND regexp_matches(value, '[A-Za-z]') AND len(list_distinct(string_split(value, ''))) >= {LEAST_DISTINCT}) x FROM a GROUP BY 1),
j AS (SELECT a.*, CASE WHEN r >= {COPIED_REPOSITORIES} AND w >= {COPIED_OWNERS} THEN 'example' WHEN w <= 1 AND x THEN 'live' ELSE 'unclear' END v FROM a JOIN o USING (value)),
g AS (SELECT doc_id, count(*) FILTER (kind = 'assign') na, count(*) FILTER (kind = 'access') nb, count(*) FILTER (kind = 'hex') nc,
        count(*) FILTER (v = 'live') nl, count(*) FILTER (v = 'example') ne, count(*) FILTER (v = 'unclear') nu,
        string_agg(concat(kind, ':', CAST(s AS BIGINT), ':', CAST(e AS BIGINT)), ',' ORDER BY s, rank) FILTER (rank < 3) b,
        string_agg(concat(kind, ':', CAST(s AS BIGINT), ':', CAST(e AS BIGINT)), ',' ORDER BY s, rank) sp FROM j GROUP BY 1)
SELECT doc_id, coalesce(na, 0) n_assign, coalesce(nb, 0) n_access, coalesce(nc, 0) n_hex, sha256(coalesce(b, '')) base_sha256, coalesce(sp, '') spans,
       coalesce(nl, 0) n_live, coalesce(ne, 0) n_example, coalesce(nu, 0) n_unclear FROM documents LEFT JOIN g USING (doc_id)"""


ORACLE = _oracle()
