"""Set-similarity join on word shingles: rare-first prefixes, length, positional and suffix filters.

Every document is the set of its distinct word shingles.  Documents with equal
sets form a class that one representative stands for.  Shingles are ordered
rare-first: frequent ones (found with their counts over all documents) come
last, by count; the others come by hash.  The order only steers cost, any order
gives the same links.  A set's prefix is what two sets with the wanted similarity
must share a shingle of.

Rows (prefix shingle, set, size, position) meet by shingle.  They are the largest thing
that is shuffled, so a row is short: the upper 44 bits of a shingle's hash share a number
with the position, and set and size, which a set's rows repeat, stand side by side.
Shingles that agree in 44 bits only add candidates, and a position that is too large for
its 20 bits counts as an earlier one, which filters less; every pair is verified on whole
sets.  Instead of all pairs of a group, three passes find the same components:

1. every set is verified against one lead, the least set of most of its groups, if they
   share half of the prefix shingles that similar sets of their sizes share;
2. where hot groups still hold several components and far more pairs than rows, their
   sets are verified against further leads, as long as that links many: at first the set
   with most of its prefix in hot groups (the original of many copies has no shingles of
   its own), then sets drawn by hash;
3. sets that share a prefix shingle but lie in different components so far are
   paired, filtered by length, position and the number of prefix shingles that
   similar sets of their sizes must share, and each pair is verified once.

Pairs inside one component can add no link between components, so no component
is missed and a group of copies costs its size, not its square.  Verification
runs the suffix filter before it intersects the sets.

A document without words has an empty set, links with nothing and is its own
component; fewer than `size` words make one shingle.  Null text is empty text.
A node is a 64-bit hash of id and text: repeated rows are one node, while rows that
share an id, or have none, but differ in text are nodes of their own.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import components, keep, mix, release, shingles, ship, small, steps

#: Shingles that are ordered by their counts; all others count as equally rare.
FREQUENT = 200_000
#: Sets that share a shingle from which the group counts as hot.
HOT_GROUP = 64
#: Bytes of sets that a verification may broadcast.
SET_BYTES = 8 << 20
#: Hot groups are crowded if their pairs outnumber their rows by this; rounds of leads at most.
ROUND_FROM, MOST_ROUNDS = 64, 6
#: Shingles whose repeats are counted together.
COUNTED = 4_000_000
SUFFIX_DEPTH = 3
#: Bits of a prefix row's number that hold the position; the others are the shingle's.
PLACE_BITS = 20


def prefix_length(n: int, num: int, den: int) -> int:
    """Shingles of a set of n of which a set with similarity num/den must share one."""
    return n - -(-n * num // den) + 1 if n else 0


def packed(shingle: np.ndarray, pos: np.ndarray) -> np.ndarray:
    """Upper bits of each shingle and its position, or the last one that fits, as one number."""
    low = np.uint64((1 << PLACE_BITS) - 1)
    return (shingle & ~low | np.minimum(pos.astype(np.uint64), low)).view(np.int64)


def ordered(s: np.ndarray, frequent: np.ndarray, place: np.ndarray) -> np.ndarray:
    """Shingles rare-first; a position in the global order replaces nothing but the sequence."""
    if not len(frequent) or not len(s):
        return s
    at = np.minimum(np.searchsorted(frequent, s), len(frequent) - 1)
    late = np.where(frequent[at] == s, place[at] + 1, 0)
    return s[np.lexsort((s, late))]


def suffix_bound(a: np.ndarray, b: np.ndarray, depth: int = SUFFIX_DEPTH) -> int:
    """Least number of elements by which two sorted sets differ, by cutting both at medians."""
    if not depth or not len(a) or not len(b):
        return abs(len(a) - len(b))
    mid = len(b) // 2
    at = int(np.searchsorted(a, b[mid]))
    hit = at < len(a) and a[at] == b[mid]
    return suffix_bound(a[:at], b[:mid], depth - 1) + suffix_bound(a[at + hit :], b[mid + 1 :], depth - 1) + (not hit)


def similar(a: np.ndarray, b: np.ndarray, num: int, den: int) -> bool:
    """den * intersection >= num * union, of sorted sets."""
    n = len(a) + len(b)
    need = -(-num * n // (num + den))  # least intersection
    if suffix_bound(a, b) > n - 2 * need:
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return den * both >= num * (n - both)


def _join_ids(df: DataFrame, ids: DataFrame, spark: SparkSession, how: str) -> DataFrame:
    return df.join(small(ids, spark), "id", how)


def node_key(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> Column:
    return F.xxhash64(docs[id_col], docs[text_col])


def join(docs: DataFrame, spark: SparkSession, num: int = 75, den: int = 100, size: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, n_shingles, component_id (least id of the component, null if no row of it has one) for
    every row (ids as long), and component_key, which tells components apart whose ids do not."""
    out = linked(docs, spark, num, den, size, id_col, text_col)
    return out.select(F.col("id").alias(id_col), "n_shingles", "component_id", F.col("component").alias("component_key"))


def linked(docs: DataFrame, spark: SparkSession, num: int = 75, den: int = 100, size: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """node, id, n_shingles, component (least node), component_id (least id) for every row."""
    ship(spark)
    # In what follows the node is called id; ids travel as strings, since pandas has no null integers.
    source = docs.select(node_key(docs, id_col, text_col).alias("id"), docs[id_col].cast("long").cast("string").alias("own"), docs[text_col].alias("t"))

    # One pass: size and 128-bit fingerprint of every set, and counts of repeated shingles.
    def survey(batches):
        import pandas as pd

        for pdf in batches:
            ids, own, held = pdf["id"].to_numpy(), pdf["own"].to_numpy(), []
            for first, raw in steps(pdf["t"].tolist()):
                sets = shingles(raw, size)
                n = np.array([len(s) for s in sets])
                with np.errstate(over="ignore"):
                    h1 = np.array([s.sum(dtype=np.uint64) for s in sets], np.uint64)
                    h2 = np.array([np.bitwise_xor.reduce(mix(s)) if len(s) else 0 for s in sets], np.uint64)
                yield pd.DataFrame({"id": ids[first : first + len(raw)], "own": own[first : first + len(raw)], "n": n, "h1": h1.view(np.int64), "h2": h2.view(np.int64), "doc": True})
                held += sets
                if sum(map(len, held)) > COUNTED or first + len(raw) == len(ids):
                    v, c = np.unique(np.concatenate(held), return_counts=True)
                    held, some = [], c >= 3
                    if some.any():
                        yield pd.DataFrame({"id": 0, "own": None, "n": c[some], "h1": v[some].view(np.int64), "h2": 0, "doc": False})

    seen = keep(source.mapInPandas(survey, "id long, own string, n long, h1 long, h2 long, doc boolean"), spark)
    sets = seen.filter("doc").select("id", F.col("own").cast("long").alias("own"), "n", "h1", "h2")
    often = seen.filter("not doc").groupBy("h1").agg(F.sum("n").alias("c")).orderBy(F.desc("c"), "h1").limit(FREQUENT).collect()
    keys = np.array([r.h1 for r in often], np.int64).view(np.uint64)
    by = np.argsort(keys)
    frequent = spark.sparkContext.broadcast((keys[by], len(keys) - 1 - by))  # most frequent last

    # Sets that occur twice or more, and who has them; a row that repeats is one node.
    classes = keep(sets.filter("n > 0").groupBy("h1", "h2", "n").agg(F.min("id").alias("rep"), F.count("*").alias("m")).filter("m > 1").drop("m"), spark)
    members = keep(sets.join(small(classes, spark), ["h1", "h2", "n"]).groupBy("id", "rep").agg(F.count("*").alias("times")), spark)
    copies = members.filter("id <> rep").select("id", "rep")
    again = keep(members.filter("id = rep and times > 1").select("id"), spark)
    if again.limit(1).count():
        source = _join_ids(source, again, spark, "left_anti").union(_join_ids(source, again, spark, "left_semi").dropDuplicates(["id"]))
    alone = _join_ids(source, copies.select("id"), spark, "left_anti")

    def prefixes(batches):
        import pandas as pd

        freq, place = frequent.value
        for pdf in batches:
            ids = pdf["id"].to_numpy()
            for first, raw in steps(pdf["t"].tolist()):
                part, who, n = [], [], []
                for i, s in enumerate(shingles(raw, size)):
                    p = ordered(s, freq, place)[: prefix_length(len(s), num, den)]
                    part.append(p)
                    who.append(len(p))
                    n.append(len(s))
                which = np.repeat(np.arange(len(raw)), who)
                pos = np.concatenate([np.arange(k) for k in who]) if len(which) else which
                yield pd.DataFrame({"kp": packed(np.concatenate(part), pos), "id": ids[first : first + len(raw)][which], "n": np.array(n, np.int64)[which]})

    # Dealt out as packed; the window finds them dealt by k.
    shingle = F.shiftright("kp", PLACE_BITS)
    met = alone.mapInPandas(prefixes, "kp long, id long, n long").repartition(shingle)
    listed = met.select(shingle.alias("k"), "id", F.shiftleft("n", 32).bitwiseOR(F.col("kp").bitwiseAND((1 << PLACE_BITS) - 1)).alias("np"))
    w = W.partitionBy("k")
    n_of = lambda c: F.shiftright(F.col(c), 32)
    least = F.min(F.struct("id", n_of("np").alias("n"))).over(w)
    groups = keep(listed.withColumn("lead", least).withColumn("last", F.max("id").over(w)).filter("lead.id <> last").drop("last"), spark)
    need = F.expr(f"ceil({num} * (n1 + n2) / {num + den}.0)")
    prefix = lambda n: F.expr(f"{n} - ceil({num} * {n} / {den}.0) + 1")
    fewest = F.least(prefix("n1") - F.col("n1") + need, prefix("n2") - F.col("n2") + need)
    led = groups.filter("id <> lead.id").groupBy("id", n_of("np").alias("n2"), F.col("lead.id").alias("lead"), F.col("lead.n").alias("n1")).agg(F.count("*").alias("c"))
    led = led.filter((num * F.col("n1") <= den * F.col("n2")) & (num * F.col("n2") <= den * F.col("n1")) & (2 * F.col("c") >= fewest))
    first = keep(led.groupBy("id").agg(F.max_by("lead", F.struct("c", -F.col("lead"))).alias("a")).select("a", F.col("id").alias("b")), spark)

    def verified(pairs: DataFrame) -> DataFrame:
        """(src, dst) of the pairs (a, b) that are similar."""
        need = keep(pairs.select(F.col("a").alias("id")).union(pairs.select("b")).distinct(), spark)

        def whole(batches):
            import pandas as pd

            for pdf in batches:
                ids = pdf["id"].to_numpy()
                for at, raw in steps(pdf["t"].tolist()):
                    yield pd.DataFrame({"id": ids[at : at + len(raw)], "s": [s.tobytes() for s in shingles(raw, size)]})

        full = keep(_join_ids(source, need, spark, "left_semi").mapInPandas(whole, "id long, s binary"), spark)

        def check(batches):
            import pandas as pd

            for pdf in batches:
                ok = [similar(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), num, den) for x, y in zip(pdf["sa"], pdf["sb"], strict=True)]
                yield pd.DataFrame({"src": pdf["a"][ok], "dst": pdf["b"][ok]})

        both = pairs.join(small(full.select(F.col("id").alias("a"), F.col("s").alias("sa")), spark, SET_BYTES), "a").join(small(full.select(F.col("id").alias("b"), F.col("s").alias("sb")), spark, SET_BYTES), "b")
        out = keep(both.select("a", "b", "sa", "sb").mapInPandas(check, "src long, dst long"), spark)
        release(spark, full)
        return out

    # Pass 1.
    links = verified(first)
    comp = keep(components(links, spark), spark)

    n1, n2, p1, p2 = map(F.col, ("n1", "n2", "p1", "p2"))
    length = (num * n1 <= den * n2) & (num * n2 <= den * n1)
    size_of, place_of = n_of("np"), F.col("np").bitwiseAND(0xFFFFFFFF)
    # In a frequent shingle's group the smaller set must have it early: its first shared shingle leaves room for what it needs.
    is_early = size_of - place_of >= F.expr(f"ceil({num} * 2 * shiftright(np, 32) / {num + den}.0)")

    def mixed_groups(rows: DataFrame, comp: DataFrame) -> tuple[DataFrame, DataFrame, bool]:
        """(rows of groups with several components, each set's rows in hot ones, whether these would give too many pairs)."""
        node = comp.select(F.col("node").alias("id"), "component")
        placed = rows.select("k", "id", "np").join(small(node, spark), "id", "left").withColumn("component", F.coalesce("component", "id"))
        mixed = placed.groupBy("k").agg(F.min("component").alias("lo"), F.max("component").alias("hi"), F.count("*").alias("m"), F.count_if(is_early).alias("e")).filter("lo < hi")
        rows = keep(placed.join(mixed.select("k", "e", (F.col("m") > HOT_GROUP).alias("hot")), "k"), spark)
        times = keep(rows.filter("hot").groupBy("id").agg(F.count("*").alias("h"), F.sum("e").alias("e")), spark)
        met, many = times.agg(F.sum("e"), F.sum("h")).first()  # the sum of e over a group's m rows is e * m
        return rows.drop("e"), times.select("id", "h"), (met or 0) > ROUND_FROM * (many or 0)

    # Pass 2: sets of crowded hot groups against one more lead each time, while that links many of them.
    rest, times, crowded = mixed_groups(groups, comp)
    release(spark, groups)
    usual, hot = rest.filter("not hot"), rest.filter("hot")
    for turn in range(MOST_ROUNDS) if crowded else ():
        at = F.struct("id", size_of.alias("n"), "component")
        lead = hot.join(small(times, spark), "id").groupBy("k").agg(F.max_by(at, F.struct(F.col("h") if turn == 0 else F.lit(0), F.xxhash64("id", F.lit(turn)))).alias("lead"))
        cand = hot.join(lead, "k").filter("component <> lead.component").select("id", size_of.alias("n1"), F.col("lead.id").alias("lead"), F.col("lead.n").alias("n2")).filter(length)
        cand = cand.groupBy("id", "lead").agg(F.count("*").alias("c"))
        tried = keep(cand.groupBy("id").agg(F.max_by("lead", F.struct("c", "lead")).alias("a")).select("a", F.col("id").alias("b")), spark)
        new = verified(tried)
        n_new, n_tried = new.select("dst").distinct().count(), tried.count()
        release(spark, tried)
        links = links.union(new)
        comp = keep(components(links, spark), spark)
        hot, times, crowded = mixed_groups(hot, comp)
        if not crowded or 2 * n_new < n_tried:
            break

    # Pass 3: only pairs between components.
    rest = usual.unionByName(hot).join(small(times, spark), "id", "left").withColumn("h", F.coalesce("h", F.lit(0)))
    row = [c for c in rest.columns if c not in ("k", "hot")]
    side = lambda i, which: rest.filter(which).select("k", *(F.col(c).alias(f"{c}{i}") for c in row)).withColumn(f"n{i}", n_of(f"np{i}")).withColumn(f"p{i}", F.col(f"np{i}").bitwiseAND(0xFFFFFFFF)).drop(f"np{i}")
    usual = side(1, "not hot").join(side(2, "not hot"), "k").filter((F.col("component1") < F.col("component2")) & length)
    early = side(1, F.col("hot") & is_early)
    order = (n1 < n2) | ((n1 == n2) & (F.col("id1") < F.col("id2")))
    often_ = early.join(side(2, "hot"), "k").filter(order & (F.col("component1") != F.col("component2")) & length & (F.least(n1 - p1, n2 - p2) >= need))
    met = usual.withColumn("c", F.lit(1)).unionByName(often_.withColumn("c", F.lit(0)))
    first_is = F.col("id1") < F.col("id2")
    pick = lambda c, d: F.when(first_is, F.col(c)).otherwise(F.col(d))
    met = met.select(*(pick(f"{c}{i}", f"{c}{3 - i}").alias(f"{c}{i}") for c in ("id", "n", "p", "h") for i in (1, 2)), "c")
    met = met.groupBy("id1", "id2", "n1", "n2", "h1", "h2").agg(F.sum("c").alias("c"), F.min("p1").alias("p1"), F.min("p2").alias("p2"))
    met = met.filter((F.least(n1 - p1, n2 - p2) >= need) & (F.col("c") + F.least("h1", "h2") >= fewest))
    pairs = met.select(F.least("id1", "id2").alias("a"), F.greatest("id1", "id2").alias("b")).join(first.select("a", "b"), ["a", "b"], "left_anti")
    pairs = keep(pairs, spark)
    more = verified(pairs)
    release(spark, pairs, first)
    if more.limit(1).count():
        comp = keep(components(links.union(more), spark), spark)

    reps = sets.select("id", "own", "n").join(small(copies, spark), "id", "left").withColumn("node", F.coalesce("rep", "id"))
    out = keep(reps.join(small(comp, spark), "node", "left").select("id", "own", "n", F.coalesce("component", "node").alias("component")), spark)
    named = keep(out.groupBy("component").agg(F.min("own").alias("component_id"), F.count("*").alias("m")).filter("m > 1").drop("m"), spark)
    out = out.join(small(named, spark), "component", "left")
    return out.select(F.col("id").alias("node"), F.col("own").alias("id"), F.col("n").alias("n_shingles"), "component", F.coalesce("component_id", "own").alias("component_id"))
