"""Links inside groups of sets that share keys, told by what sets each apart from its group's centre.

Every set that shares a key goes to the group of its heaviest neighbour, the hub. The centre H of a group
holds the tokens of most of its members. A member x is kept as its differences: the tokens A that H lacks
and the tokens G of H that it lacks. With a = |A| + |G|, n = |x|, p percent, q = 100 + p and r = 100 - p,
let w = q a - r n. Two members with s common differences are linked just if 2 q s >= w + w'.

* If w + w' <= 0 they are linked whatever they share. All such links lead to the same classes as those to
  the member of least w alone: a star, one row a member. Only members with w > -min(w), the outliers, are
  not in it, and only pairs with an outlier are looked at any further.
* Pairs that share an added token meet by it: prefixes of A, rarest tokens of the group first.
* Pairs that share no added token have |H| - |G or G'| common tokens at most, so the size of each is
  bounded by what the other lacks; those few meet by prefixes of G.

What meets is compared by its differences. Where a token is common to a large part of a group (a version
among versions), the sets that have it as a key form groups of their own, with their own centres, as long
as that halves the number of pairs left at least. No link is lost whichever way a pair is met.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import saved

#: Pairs a key row that are cheaper to compare than to group anew.
PAIRS_A_ROW = 4


def _over(a: Column, b: Column | int) -> Column:
    """a / b rounded up, for whole numbers of either sign."""
    return F.ceil(a / b).cast("long")


def hubs(keys: DataFrame) -> DataFrame:
    """(node, hub) for every node of keys(key, node): of its keys' heaviest nodes the heaviest; a node weighs what its keys hold."""
    keys = keys.select("key", "node")
    sizes = keys.groupBy("key").agg(F.count("*").alias("n"))
    weight = saved(keys.join(sizes, "key").groupBy("node").agg(F.sum("n").alias("w")))
    pivot = saved(keys.join(weight, "node").groupBy("key").agg(F.max(F.struct("w", "node")).alias("p")))
    return saved(keys.join(pivot, "key").groupBy("node").agg(F.max("p").alias("p")).select("node", F.col("p.node").alias("hub")))


def _from_hubs(hub_of: DataFrame, sets: DataFrame) -> DataFrame:
    """Members, hubs among them, with the tokens that their hub lacks and those of the hub that they lack."""
    members = hub_of.unionByName(hub_of.select(F.col("hub").alias("node"), "hub")).distinct()
    own, centre = sets.select("node", "tokens"), sets.select(F.col("node").alias("hub"), F.col("tokens").alias("middle"))
    both = members.join(own, "node").join(centre, "hub")
    return saved(both.select("hub", "node", F.size("tokens").cast("long").alias("n"), F.size("middle").cast("long").alias("h"), F.array_except("tokens", "middle").alias("added"), F.array_except("middle", "tokens").alias("gone")))


def _token_rows(rows: DataFrame) -> DataFrame:
    """One row a difference: (hub, token, kind), kind 0 for added ones."""
    marked = lambda c, kind: F.transform(c, lambda t: F.struct(t.alias("token"), F.lit(kind).alias("kind")))
    return rows.select("hub", "node", F.explode(F.concat(marked("added", 0), marked("gone", 1))).alias("d")).select("hub", "node", "d.token", "d.kind")


def _centred(apart: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(members against the tokens that most members have; (hub, token, kind, f) of differences that several have)."""
    counts = apart.groupBy("hub").agg(F.count("*").alias("members"))
    large = saved(counts.where("members > 2"))
    shared = saved(_token_rows(apart.join(large, "hub", "left_semi")).groupBy("hub", "token", "kind").agg(F.count("*").alias("f")).where("f > 1"))
    shared = shared.join(large, "hub").withColumn("moved", F.col("f") * 2 > F.col("members"))
    moved = saved(shared.where("moved").groupBy("hub").agg(F.collect_list(F.when(F.col("kind") == 0, F.col("token"))).alias("into"), F.collect_list(F.when(F.col("kind") == 1, F.col("token"))).alias("out")))
    none = F.array().cast("array<long>")
    rows = apart.join(moved, "hub", "left").withColumn("into", F.coalesce("into", none)).withColumn("out", F.coalesce("out", none))
    added = F.concat(F.array_except("added", "into"), F.array_except("out", "gone"))
    gone = F.concat(F.array_except("gone", "out"), F.array_except("into", "added"))
    rows = rows.select("hub", "node", "n", (F.col("h") + F.size("into") - F.size("out")).alias("h"), added.alias("added"), gone.alias("gone"))
    now = F.when(F.col("moved"), F.col("members") - F.col("f")).otherwise(F.col("f"))
    kind = F.when(F.col("moved"), 1 - F.col("kind")).otherwise(F.col("kind"))
    return rows, shared.select("hub", "token", kind.alias("kind"), now.alias("f"))


def _prefixes(rows: DataFrame, shared: DataFrame, percent: int) -> DataFrame:
    """Keys (key, hub, node, kind, ...) by which the linked pairs with an outlier meet."""
    q, r, p = 100 + percent, 100 - percent, percent
    few = rows.select("hub", "node", "n", "h", "w", "least", "fewest", F.size("added").cast("long").alias("na"), F.size("gone").cast("long").alias("ng"), F.col("out"))
    few = few.withColumn("room", F.floor(q * (F.col("h") - F.col("ng")) / p).cast("long") - F.col("n"))  # most tokens of a partner without a common added one
    smallest = F.greatest("fewest", _over(p * F.col("n"), 100))
    needs_added = F.greatest(F.lit(1), _over(p * (F.col("n") + smallest), q) - F.col("h") + F.col("ng"))
    w_other = F.when(F.col("out"), F.greatest("least", F.col("w") - 2 * r * _over(100 * F.col("n"), p))).otherwise(1 - F.col("least"))
    needs_gone = F.greatest(F.lit(1), _over(F.col("w") + w_other, 2 * q))
    few = few.withColumn("needs", F.array(needs_added, needs_gone)).withColumn("many", F.array("na", "ng"))
    # Tokens that no other member has meet nobody; they only take the first places.
    told = _token_rows(rows).join(shared.where("f > 1"), ["hub", "token", "kind"]).groupBy("hub", "node", "kind").agg(F.sort_array(F.collect_list(F.struct("f", "token"))).alias("held"))
    told = told.join(few, ["hub", "node"]).withColumn("many", F.get("many", F.col("kind"))).withColumn("needs", F.get("needs", F.col("kind")))
    before = F.col("many") - F.size("held")
    cut = F.slice("held", 1, F.least(F.size("held"), F.greatest(F.lit(0), (F.col("many") - F.col("needs") + 1 - before).cast("int"))))
    each = F.transform(cut, lambda t, i: F.struct(t["token"].alias("token"), (F.col("many") - before - i).cast("long").alias("left")))
    posted = told.select("hub", "node", "kind", "n", "h", "w", "na", "ng", "room", "out", F.explode(each).alias("e"))
    return posted.select(F.xxhash64("hub", "e.token", "kind").alias("key"), "hub", "node", "kind", "n", "h", "w", "na", "ng", "room", "out", F.col("e.left").alias("left"))


def _meeting(keys: DataFrame, hub_of: DataFrame | None, percent: int) -> DataFrame:
    """Pairs (hub, a, b) that share a key and may be linked by what is known of their sizes."""
    q, p = 100 + percent, percent
    keys = keys if hub_of is None else keys.join(hub_of.select("node", F.col("hub").alias("sub")), "node")
    x, y = keys.alias("x"), keys.alias("y")
    least, most = lambda c: F.least(f"x.{c}", f"y.{c}"), lambda c: F.greatest(f"x.{c}", f"y.{c}")
    meet = (F.col("x.key") == F.col("y.key")) & (F.col("x.hub") == F.col("y.hub")) & (F.col("x.node") < F.col("y.node")) & (F.col("x.out") | F.col("y.out")) & (100 * least("n") >= p * most("n"))
    both_w, sizes = F.col("x.w") + F.col("y.w"), F.col("x.n") + F.col("y.n")
    added = (2 * q * F.least(F.col("x.na") + F.col("x.ng"), F.col("y.na") + F.col("y.ng")) >= both_w) & (q * (least("left") + F.col("x.h") - most("ng")) >= p * sizes)
    gone = (F.col("y.n") <= F.col("x.room")) & (F.col("x.n") <= F.col("y.room")) & (2 * q * least("left") >= both_w)
    meet = meet & F.when(F.col("x.kind") == 0, added).otherwise(gone)
    if hub_of is not None:
        meet = meet & (F.col("x.sub") != F.col("y.sub")) & (F.col("x.sub") != F.col("y.node")) & (F.col("y.sub") != F.col("x.node"))
    return x.join(y, meet).select("x.hub", F.col("x.node").alias("a"), F.col("y.node").alias("b")).distinct()


def _compared(pairs: DataFrame, rows: DataFrame, percent: int) -> DataFrame:
    """The linked ones of pairs (hub, a, b), by their differences."""
    one = lambda t, node: rows.select("hub", F.col("node").alias(node), F.col("w").alias(f"w{t}"), F.col("added").alias(f"added{t}"), F.col("gone").alias(f"gone{t}"))
    both = saved(pairs).join(one("x", "a"), ["hub", "a"]).join(one("y", "b"), ["hub", "b"])
    common = F.size(F.array_intersect("addedx", "addedy")) + F.size(F.array_intersect("gonex", "goney"))
    return both.where(2 * (100 + percent) * common >= F.col("wx") + F.col("wy")).select("a", "b")


def _load(keys: DataFrame) -> tuple[int, int]:
    """(key rows, pairs with an outlier that share a key)."""
    held = keys.groupBy("key").agg(F.count("*").alias("n"), F.sum(F.col("out").cast("long")).alias("o"))
    row = held.agg(F.sum("n").alias("n"), F.sum((F.col("o") * (F.col("o") - 1) / 2 + F.col("o") * (F.col("n") - F.col("o"))).cast("double")).alias("p")).first()
    return int(row["n"] or 0), int(row["p"] or 0)


def linked_in_groups(hub_of: DataFrame, sets: DataFrame, percent: int) -> list[DataFrame]:
    """Edges (a, b) that connect all members of a group that links between its members connect.

    Groups are formed anew while that halves the pairs left.
    """
    edges: list[DataFrame] = []
    pairs_before: float = float("inf")
    while True:
        rows, shared = _centred(_from_hubs(hub_of, sets))
        rows = saved(rows.withColumn("w", (100 + percent) * (F.size("added") + F.size("gone")) - (100 - percent) * F.col("n")))
        stars = rows.groupBy("hub").agg(F.min(F.struct("w", "node")).alias("star"), F.min("n").alias("fewest"), F.max("w").alias("top"))
        stars = saved(stars.select("hub", F.col("star.w").alias("least"), F.col("star.node").alias("star"), "fewest", (F.col("top") > -F.col("star.w")).alias("open")))
        starred = rows.join(stars, "hub")
        edges.append(starred.where((F.col("w") + F.col("least") <= 0) & (F.col("node") != F.col("star"))).select(F.col("node").alias("a"), F.col("star").alias("b")))
        rest = starred.where("open").withColumn("out", F.col("w") > -F.col("least"))
        posted = saved(_prefixes(rest, shared, percent))
        useful = saved(posted.groupBy("key").agg(F.count("*").alias("n"), F.max("out").alias("o")).where("n > 1 and o").select("key"))
        posted = saved(posted.join(useful, "key"))
        n, pairs = _load(posted)
        if pairs <= PAIRS_A_ROW * n or pairs > pairs_before / 2:
            edges.append(_compared(_meeting(posted, None, percent), rows, percent))
            return edges
        hub_of, pairs_before = hubs(posted.select("key", "node").distinct()), pairs
        edges.append(_compared(_meeting(posted, hub_of, percent), rows, percent))


__all__ = ["hubs", "linked_in_groups"]

