"""Secret scan by linking the parts of a credential.

Strong findings (keyword assignments, access keys, long hex strings) are reported as they are. Weak
parts - identifiers, unlabelled random-looking strings and endpoints - are harmless alone; an interval
join within a scope of ``SCOPE`` code points reports them only beside a complementary part.

Everything is DataFrame functions. Spans are code points, end exclusive. A null text is empty; an
empty table gives no rows; rows that repeat get the same result each; other columns pass unread.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import saved, table

#: Fixed patterns of the base findings.
ASSIGN = (
    r"([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])"
    r"[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
)
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]{24,}"  # the same spans as runs of any length of which those under 24 are dropped
#: Weak parts.
IDENTIFIER = r"(?:client_id|access_key_id|user_?name|login|account_id)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9_.@-]+)"
OPAQUE = r"(?<![A-Za-z0-9+/])[A-Za-z0-9+/]{32,}={0,2}(?![A-Za-z0-9+/=])"
ENDPOINT = r"(?:https?|postgres|postgresql|mysql|mongodb|redis|amqp|s3|ftp)://[^\x20\x09-\x0D\"'<>]+"

KINDS = ("assign", "access", "hex", "identifier", "opaque", "endpoint")
#: What a kind is (1 identifies, 2 is secret, 4 is a place), and for weak kinds what must be near.
ROLE = {"assign": 2, "access": 1, "hex": 2, "identifier": 1, "opaque": 2, "endpoint": 4}
NEEDS = {"identifier": 2, "opaque": 1 | 4, "endpoint": 2}
SCOPE, BIN, CHUNK = 160, 512, 64
_NO_SPANS = "cast(array() as array<struct<rank:int,start:int,end:int>>)"


def _found(text: Column, kind: str, pattern: str, keep=None, group: int = 0) -> Column:
    """Array of (kind rank, start, end): pieces between matches give the places, their own texts the lengths."""
    hits = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    parts = F.arrays_zip(
        F.transform(F.split(text, pattern, -1), lambda g: F.length(g)).alias("gap"),
        F.transform(hits, lambda h: F.length(h)).alias("hit"),
        (F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else hits).alias("own"),
    )
    # Places are sums of what goes before. In chunks, so that a text with very many hits is not copied for each.
    chunks = F.transform(F.sequence(F.lit(0), F.floor((F.size(parts) - 1) / CHUNK).cast("int")), lambda i: F.slice(parts, i * CHUNK + 1, CHUNK))
    length = lambda p: p["gap"] + F.coalesce(p["hit"], F.lit(0))
    sums = F.transform(chunks, lambda c: F.aggregate(c, F.lit(0), lambda n, p: n + length(p)))
    begins = F.aggregate(sums, F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<int>)").alias("out")), lambda a, n: F.struct((a["at"] + n).alias("at"), F.concat(a["out"], F.array(a["at"])).alias("out")), lambda a: a["out"])

    def step(acc: Column, p: Column) -> Column:
        begin = acc["at"] + p["gap"]
        one = F.array(F.struct(F.lit(KINDS.index(kind)).alias("rank"), begin.alias("start"), (acc["at"] + length(p)).alias("end")))
        good = p["hit"].isNotNull() & (keep(p["own"]) if keep else F.lit(True))
        return F.struct((acc["at"] + length(p)).alias("at"), F.when(good, F.concat(acc["out"], one)).otherwise(acc["out"]).alias("out"))

    folded = F.flatten(F.zip_with(chunks, begins, lambda c, at: F.aggregate(c, F.struct(at.alias("at"), F.expr(_NO_SPANS).alias("out")), step, lambda acc: acc["out"])))
    return F.when(F.size(hits) > 0, folded).otherwise(F.expr(_NO_SPANS))


def _parts(text: Column) -> Column:
    """All parts of a text, strong and weak; weak ones that overlap a strong one are left out later."""
    mixed = lambda s: s.rlike("[0-9]") & s.rlike("[a-z]") & s.rlike("[A-Z]")
    return F.concat(
        _found(text, "assign", ASSIGN, lambda s: F.length(s) >= 6, 2),
        _found(text, "access", ACCESS, lambda s: F.length(s) >= 20),
        _found(text, "hex", HEX),
        _found(text, "identifier", IDENTIFIER, lambda s: F.length(s) >= 3, 1),
        _found(text, "opaque", OPAQUE, mixed),
        _found(text, "endpoint", ENDPOINT),
    )


def _joined(spans: Column) -> Column:
    """kind:start:end by start, then kind as listed, then end."""
    ordered = F.array_sort(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["rank"].alias("rank"), s["end"].alias("end"))))
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(ordered, lambda s: F.concat_ws(":", F.element_at(names, s["rank"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def linked_spans(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``(key, k1, k2, base, spans)`` per row: strong spans, and those plus the linked weak ones.

    ``k1``, ``k2`` hash the key and the text, so that rows with null or repeated keys stay apart (rows
    alike in both have the same spans anyway).
    """
    base_ranks, weak = len(KINDS) - len(NEEDS), [KINDS.index(k) for k in NEEDS]
    whole = F.coalesce(F.col(text), F.lit(""))
    seen = saved(
        docs.select(F.col(key).alias(key), F.xxhash64(F.lit(1), F.col(key), whole).alias("k1"), F.xxhash64(F.lit(2), whole, F.col(key)).alias("k2"), _parts(whole).alias("parts"))
    )
    seen = seen.withColumn("base", F.filter("parts", lambda s: s["rank"] < base_ranks))
    role = F.element_at(F.array(*[F.lit(ROLE[k]) for k in KINDS]), F.col("p.rank") + 1)
    needs = F.element_at(F.array(*[F.lit(NEEDS.get(k, 0)) for k in KINDS]), F.col("p.rank") + 1)
    linkable = seen.where(F.exists("parts", lambda s: s["rank"].isin(weak)) & (F.size("parts") > 1)).dropDuplicates(["k1", "k2"])
    flat = linkable.select("k1", "k2", F.explode("parts").alias("p"))
    bins = lambda lo, hi: F.explode(F.sequence(F.floor(lo / BIN), F.floor((hi - 1) / BIN)))
    # A part lies in every bin of its scope; a bin holds a bounded number of parts, so no group of rows is hot.
    near = flat.select("k1", "k2", role.alias("role"), (F.col("p.start") - SCOPE).alias("lo"), (F.col("p.end") + SCOPE).alias("hi"))
    near = near.withColumn("bin", bins(F.col("lo"), F.col("hi")))
    strong = flat.where(F.col("p.rank") < base_ranks).select("k1", "k2", F.col("p.start").alias("lo"), F.col("p.end").alias("hi"), bins(F.col("p.start"), F.col("p.end")).alias("bin"))
    asking = flat.where(F.col("p.rank").isin(weak)).select("k1", "k2", "p", needs.alias("needs"), bins(F.col("p.start"), F.col("p.end")).alias("bin"))
    a, n = asking.alias("a"), near.alias("n")
    there = lambda t: (F.col("a.k1") == F.col(f"{t}.k1")) & (F.col("a.k2") == F.col(f"{t}.k2")) & (F.col("a.bin") == F.col(f"{t}.bin")) & (F.col(f"{t}.lo") < F.col("a.p.end")) & (F.col(f"{t}.hi") > F.col("a.p.start"))
    met = a.join(n, there("n") & (F.col("a.needs").bitwiseAND(F.col("n.role")) != 0), "left_semi").select("k1", "k2", "p", F.lit(False).alias("under"))
    under = a.join(strong.alias("s"), there("s"), "left_semi").select("k1", "k2", "p", F.lit(True).alias("under"))  # a strong one has said it
    met = met.unionByName(under).groupBy("k1", "k2", "p").agg(F.max("under").alias("under")).where("not under")
    added = met.groupBy("k1", "k2").agg(F.collect_set("p").alias("added"))
    out = seen.drop("parts").join(added, ["k1", "k2"], "left")
    return out.withColumn("spans", F.concat("base", F.coalesce("added", F.expr(_NO_SPANS)))).drop("added")


def secret_digest(docs: DataFrame) -> DataFrame:
    count = lambda k: F.size(F.filter("base", lambda s: s["rank"] == KINDS.index(k))).cast("long").alias(f"n_{k}")
    found = linked_spans(docs)
    return found.select("doc_id", *[count(k) for k in ("assign", "access", "hex")], F.sha2(_joined(F.col("base")), 256).alias("base_sha256"), _joined(F.col("spans")).alias("spans"))


def redact(docs: DataFrame, mark: str = "[SECRET]") -> DataFrame:
    """``docs`` with every reported span replaced by ``mark`` (overlapping spans by one mark)."""
    whole = F.coalesce(F.col("text"), F.lit(""))
    # All columns in one, so that none can clash with those of the join.
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"), "text", F.xxhash64(F.lit(1), F.col("doc_id"), whole).alias("k1"), F.xxhash64(F.lit(2), whole, F.col("doc_id")).alias("k2"))
    found = linked_spans(docs).where(F.size("spans") > 0).select("k1", "k2", "spans").dropDuplicates(["k1", "k2"])
    ordered = F.array_sort(F.transform("spans", lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"))))
    init = F.struct(F.lit(0).alias("at"), F.lit("").alias("out"))
    piece = lambda a, b: F.substring(F.col("text"), a + 1, F.greatest(b - a, F.lit(0)))

    def step(acc: Column, s: Column) -> Column:
        fresh = s["start"] >= acc["at"]
        return F.struct(
            F.greatest(acc["at"], s["end"]).alias("at"),
            F.when(fresh, F.concat(acc["out"], piece(acc["at"], s["start"]), F.lit(mark))).otherwise(acc["out"]).alias("out"),
        )

    clean = F.aggregate(ordered, init, step, lambda acc: F.concat(acc["out"], F.substring(F.col("text"), acc["at"] + 1, F.length("text"))))
    joined = keyed.join(found, ["k1", "k2"], "left").withColumn("text", F.when(F.col("spans").isNull(), F.col("text")).otherwise(clean))
    return joined.select(*[F.col("text") if c == "text" else F.col(f"row.`{c}`") for c in docs.columns])


def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_digest(table(spark, sf_dir, "documents").select("doc_id", "text"))
