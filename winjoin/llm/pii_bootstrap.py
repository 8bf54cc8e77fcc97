"""Personal data by fixed forms and by contextual patterns that these bootstrap, in DataFrame functions alone.

*Base spans* are what four fixed forms match (leftmost, not overlapping per
kind) and their checks accept: e-mail, IPv4 address, payment card, phone.
*Instances* are these strings and every other identifier-like one outside them: runs of 8 or more
characters with a digit, and groups of digits with blanks, brackets or other separators between them (7 digits or more); long hexadecimal runs and key-like ones seed a
fifth kind, secret; strings of a base form that its check refuses are known to be nothing. *Patterns* are the one to three tokens left of an
instance, the one or two right of it, and the pair of those next to it. Instances and patterns form a graph: each round scores a pattern by
the share of its distinct instances whose kind is known and the same (unknown ones count ``doubt`` each), accepts those
with enough support and a share near one, gives their kind to unlabelled
instances that accepted patterns reach (wherever these stand), and starts the
next round with these as seeds, until a round labels nothing. What the rounds label is added to the spans.
Tokens of a pattern stand on the instance's line, however long they are; digits count as 0.

Positions are code points. A match and the text before it (since the match
before) are one row, so a start is a running sum over the rows of a document.

Edge cases: null and empty texts have no spans; documents without instances
stay as rows; repeated rows are searched each; other columns are ignored; an
empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from winjoin.llm.frames import fresh, materialize, release

# The four forms. A run that failed at its first character fails at
# the later ones too, hence the look-behind; \G lets a match follow the one before it.
EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
IP = r"(?:(?<![0-9])|\G)[0-9]++(?:\.[0-9]++)(?:\.[0-9]++)(?:\.[0-9]++)"
CARD = r"[0-9](?:[\x20-]?[0-9])++"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
KINDS = ("email", "ip", "card", "phone")

#: Groups of digits, 7 in all or more.
GROUPS = r"(?<![A-Za-z0-9._+@%(-])(?=\(?(?:[0-9][ ()./-]{0,2}){7})\(?[0-9]{2,6}+\)?(?:[ ./-]{1,2}[0-9]{2,6}+){1,5}(?![A-Za-z0-9@]|[._+@%-][A-Za-z0-9])"
#: Other identifier-like runs, found within [A-Za-z0-9._+@%-] and kept if 8 characters long with a digit; a run is looked through once, from its start.
RUN = r"(?<![A-Za-z0-9._+@%-])(?=[A-Za-z._+@%-]*+[0-9])[A-Za-z0-9][A-Za-z0-9._+@%-]{6,}[A-Za-z0-9]"
LIKE = f"{GROUPS}|{RUN}"
SECRET = r"^(?=[0-9a-f]*[a-f])(?=[0-9a-f]*[0-9])[0-9a-f]{32,}$|^(?=[A-Za-z0-9]*[A-Z])(?=[A-Za-z0-9]*[a-z])(?=[A-Za-z0-9]*[0-9])[A-Za-z0-9]{32,}$|^AKIA[0-9A-Z]{16}$"

#: Strings of a base form that its check refuses: known to be nothing, they speak against their patterns.
REFUTED = r"^[0-9](?:[ -]?[0-9]){15,18}$|^[0-9]+(?:\.[0-9]+){3}$"
NONE = "none"

_OCTET = r"0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
#: A token of a context, whole; possessive and from its start, so that long runs are read once.
_TOKEN = r"(?:(?<![\p{L}\p{N}_])[\p{L}\p{N}_]++|[^\p{L}\p{N}_\s])"
_LEFT, _RIGHT = rf"((?:{_TOKEN}[ \t]*+){{1,3}})$", rf"^((?:[ \t]*+{_TOKEN}){{1,2}})"
#: Contexts are looked for in so many characters first, and in all of the text between two matches where these do not hold them whole.
_NEAR = 64


def _context(gap: Column, left: bool) -> Column:
    pattern, near = (_LEFT, F.right(gap, F.lit(_NEAR))) if left else (_RIGHT, F.left(gap, F.lit(_NEAR)))
    found = F.regexp_extract(near, pattern, 1)
    return F.when((F.char_length(found) == _NEAR) & (F.char_length(gap) > _NEAR), F.regexp_extract(gap, pattern, 1)).otherwise(found)


def _matches(text: str, kind: str, pattern: str, guard: Column) -> Column:
    """All matches of one form as (kind, i, gap, m, left, right): the length of the text before it (since the match before), and the tokens next to it."""
    found = F.regexp_extract_all(F.col(text), F.lit(pattern), F.lit(0))
    gaps = F.split(F.col(text), pattern, -1)
    zipped = F.arrays_zip(gaps.alias("gap"), found.alias("m"), F.slice(gaps, F.lit(2), F.greatest(F.size(gaps) - 1, F.lit(0))).alias("after"))
    zipped = F.filter(zipped, lambda z: z["m"].isNotNull())
    rows = F.transform(zipped, lambda z, i: F.struct(F.lit(kind).alias("kind"), i.alias("i"), F.char_length(z["gap"]).cast("long").alias("gap"), z["m"].alias("m"), _context(z["gap"], True).alias("left"), _context(z["after"], False).alias("right")))
    return F.when(guard & F.col(text).rlike(pattern), rows).otherwise(F.array().cast("array<struct<kind:string,i:int,gap:bigint,m:string,left:string,right:string>>"))


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    """Whether a digit string has a checksum of 0: from the right, every second digit doubled and its digits summed."""
    at = F.sequence(F.lit(1), F.greatest(F.char_length(digits), F.lit(1)))

    def add(total: Column, i: Column) -> Column:
        d = F.ascii(F.substring(digits, F.char_length(digits) - i + 1, F.lit(1))) - 48
        twice = F.when(i % 2 == 0, F.when(d * 2 > 9, d * 2 - 9).otherwise(d * 2)).otherwise(d)
        return total + twice

    return F.aggregate(at, F.lit(0), add) % 10 == 0


def _accepted(kind: Column, m: Column) -> Column:
    n = F.char_length(_digits(m))
    return (
        F.when(kind == "email", True)
        .when(kind == "ip", m.rlike(rf"^{_OCTET}(?:\.{_OCTET}){{3}}$"))
        .when(kind == "card", n.between(16, 19) & _luhn(_digits(m)))
        .when(kind == "phone", n.between(8, 15))
        .otherwise(False)
    )


def instances(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (rid, doc_id, text_hash, kind, start, end, m, left, right, base), one at least for each document (kind null).

    kind is a base kind, or 'like' for identifier-like runs outside base spans.
    """
    src = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.coalesce(F.col(f"`{text_col}`"), F.lit("")).alias("t"))
    digit = F.col("t").rlike("[0-9]")
    every = F.concat(
        _matches("t", "email", EMAIL, F.instr("t", "@") > 0), _matches("t", "ip", IP, digit), _matches("t", "card", CARD, digit),
        _matches("t", "phone", PHONE, F.instr("t", "+") > 0), _matches("t", "like", LIKE, digit),
    )
    src = src.withColumn("rid", F.monotonically_increasing_id()).withColumn("text_hash", F.xxhash64("t"))
    rows = src.select("rid", "doc_id", "text_hash", F.explode_outer(every).alias("x")).select("rid", "doc_id", "text_hash", "x.*")
    placed = Window.partitionBy("rid", "kind").orderBy("i").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    size = F.char_length("m").cast("long")
    rows = rows.withColumn("end", F.sum(F.col("gap") + size).over(placed)).withColumn("start", F.col("end") - size)
    rows = rows.withColumn("base", _accepted(F.col("kind"), F.col("m")))
    # a rejected match is no instance; its row stays for its document's sake
    rows = rows.withColumn("kind", F.when(F.col("base") | (F.col("kind") == "like"), F.col("kind")))
    # a like run that overlaps an accepted span is no instance of its own
    by_start = Window.partitionBy("rid").orderBy("start", F.when(F.col("base"), 0).otherwise(1))
    before = F.max(F.when(F.col("base"), F.col("end"))).over(by_start.rowsBetween(Window.unboundedPreceding, -1))
    after = F.min(F.when(F.col("base"), F.col("start"))).over(by_start.rowsBetween(1, Window.unboundedFollowing))
    rows = rows.withColumn("_b", before).withColumn("_a", after)
    free = (F.coalesce("_b", F.lit(-1)) <= F.col("start")) & (F.coalesce("_a", F.col("end")) >= F.col("end"))
    rows = rows.withColumn("kind", F.when((F.col("kind") == "like") & ~free, F.lit(None)).otherwise(F.col("kind")))
    return rows.select("rid", "doc_id", "text_hash", "kind", "start", "end", "m", "left", "right", F.coalesce("base", F.lit(False)).alias("base"))


def contexts(found: DataFrame) -> DataFrame:
    """The graph: distinct (m, pattern); in a pattern _ stands for the instance."""

    def tokens(c: str) -> Column:
        return F.transform(F.regexp_extract_all(F.lower(F.coalesce(c, F.lit(""))), F.lit(r"[\p{L}\p{N}_]+|[^\p{L}\p{N}_\s]"), F.lit(0)), lambda w: F.regexp_replace(w, "[0-9]", "0"))

    # an array made by a lambda stands in a column of its own before others look into it
    some = found.where("kind IS NOT NULL").select("m", tokens("left").alias("l"), tokens("right").alias("r"))
    n, k = F.size("l"), F.size("r")
    left = [F.when(n >= j, F.concat(F.array_join(F.slice("l", n - j + 1, j), " "), F.lit(" _"))) for j in (1, 2, 3)]
    right = [F.when(k >= j, F.concat(F.lit("_ "), F.array_join(F.slice("r", 1, j), " "))) for j in (1, 2)]
    both = F.when((n > 0) & (k > 0), F.concat_ws(" _ ", F.get("l", n - 1), F.get("r", F.lit(0))))
    rows = some.select("m", F.explode(F.array(*left, *right, both)).alias("pattern"))
    # a pattern names something: punctuation alone is none
    return rows.where(F.col("pattern").rlike(r"\p{L}")).distinct()


def bootstrap(found: DataFrame, rounds: int = 100, support: int = 8, share: float = 0.9, doubt: float = 0.1) -> DataFrame:
    """Labels (m, label, round) that the rounds give to instances without one.

    Rounds go on until one labels nothing; more than ``rounds`` of them are an error.
    """
    graph = materialize(contexts(found), "pii-graph")
    seeds = found.where("kind IS NOT NULL").select("m", F.when(F.col("base"), F.col("kind")).when(F.col("m").rlike(SECRET), F.lit("secret")).when(F.col("m").rlike(REFUTED), F.lit(NONE)).alias("label"))
    # an instance string has one label; where forms disagree the least name stands
    known = materialize(seeds.groupBy("m").agg(F.min("label").alias("label"), F.lit(0).alias("round")), "pii-labels")
    for r in range(1, rounds + 1):
        edges = graph.join(known, "m")
        votes = edges.groupBy("pattern", "label").agg(F.count(F.lit(1)).alias("n"))
        total = votes.groupBy("pattern").agg(F.sum("n").alias("all"), F.sum(F.when(F.col("label").isNotNull(), F.col("n"))).alias("labelled"))
        against = F.col("labelled") + F.lit(doubt) * (F.col("all") - F.col("labelled"))
        good = votes.where(F.col("label") != NONE).join(total, "pattern").where((F.col("n") >= support) & (F.col("n") >= F.lit(share) * against)).select("pattern", F.col("label").alias("got"), (F.log2(F.col("n") + 1.0) * F.col("n") / F.col("all")).alias("worth"))
        new = edges.where("label IS NULL").select("m", "pattern").join(good, "pattern").groupBy("m", "got").agg(F.sum("worth").alias("worth"))
        new = new.groupBy("m").agg(F.max_by("got", F.struct("worth", "got")).alias("got"))
        nxt = materialize(known.join(new, "m", "left").select("m", F.coalesce("label", "got").alias("label"), F.when(F.col("label").isNull() & F.col("got").isNotNull(), r).otherwise(F.col("round")).alias("round")), "pii-labels")
        grown = nxt.where(F.col("round") == r).limit(1).count()
        was, known = known, nxt
        release(was)
        if not grown:
            break
    else:
        raise RuntimeError(f"labels did not settle in {rounds} rounds")
    release(graph)
    return known.where(F.col("label") != NONE)


def find_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", rounds: int = 100, support: int = 8, share: float = 0.9, doubt: float = 0.1) -> DataFrame:
    """Rows (doc_id, text_hash, spans), one for each row of ``docs``; spans: array of (rank, start, end, kind, base), base kinds first."""
    found = materialize(instances(docs, id_col, text_col), "pii-instances")
    labels = bootstrap(found, rounds, support, share, doubt).select("m", "label")
    joined = found.join(labels, "m", "left")
    kind = F.when(F.col("base"), F.col("kind")).when(F.col("kind").isNotNull(), F.col("label"))
    rank = F.when(kind == "email", 0).when(kind == "ip", 1).when(kind == "card", 2).when(kind == "phone", 3).when(kind.isNotNull(), 4)
    span = F.when(kind.isNotNull(), F.struct(rank.alias("rank"), F.col("start"), F.col("end"), kind.alias("kind"), F.col("base")))
    return joined.select("rid", "doc_id", "text_hash", span.alias("span")).groupBy("rid").agg(F.first("doc_id").alias("doc_id"), F.first("text_hash").alias("text_hash"), F.array_sort(F.collect_list("span")).alias("spans")).drop("rid")


def spans_text(spans: Column) -> Column:
    """Spans as kind:start:end, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def redact(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``docs`` (all columns) with every span replaced by its kind in brackets; overlapping spans become one, named by the first."""
    spans = find_spans(docs, id_col, text_col, **options).where(F.size("spans") > 0)
    held, key, mine = fresh(docs.columns, "_spans", "_text_hash", "_key")
    spans = materialize(spans.groupBy(F.col("text_hash").alias(key)).agg(F.first("spans").alias(held)), "pii-spans")
    ordered = F.array_sort(F.transform(held, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"))))
    keyed = docs.withColumn(mine, F.xxhash64(F.coalesce(F.col(f"`{text_col}`"), F.lit(""))))
    wide = keyed.join(spans, F.col(mine) == F.col(key), "left")
    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.array().cast("array<string>").alias("out"))

    def take(acc: Column, s: Column) -> Column:
        text = F.col(f"`{text_col}`")
        gap = F.substring(text, (acc["at"] + 1).cast("int"), (s["start"] - acc["at"]).cast("int"))
        mark = F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]"))
        return F.when(s["start"] < acc["at"], F.struct(F.greatest(acc["at"], s["end"]).alias("at"), acc["out"].alias("out"))).otherwise(F.struct(s["end"].alias("at"), F.concat(acc["out"], F.array(gap, mark)).alias("out")))

    def close(acc: Column) -> Column:
        text = F.col(f"`{text_col}`")
        return F.concat(F.array_join(acc["out"], ""), F.substring(text, (acc["at"] + 1).cast("int"), F.char_length(text)))

    clean = F.when(F.col(held).isNull(), F.col(f"`{text_col}`")).otherwise(F.aggregate(ordered, start, take, close))
    return wide.select(*((clean.alias(c) if c == text_col else F.col(f"`{c}`")) for c in docs.columns))
