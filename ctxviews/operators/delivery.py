"""Context delivery: grep/read, eager and eager+compact policies, and their token accounting.

A replay takes recorded histories: system s, first user message q, later user
messages as observations, assistant messages as completions.  Every assistant
message is one model invocation; retained text is charged each time it is sent.
Scripted agents stand in for models: they read ranked candidates one by one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import usage

POLICIES = ("grep", "eager", "compact")
MAX_TURNS = 16
SEED_CHARS = 600
READ_CHARS = 200
COMPLETION = 12  # tokens of a scripted agent's tool call or answer


def messages(conversations: DataFrame) -> DataFrame:
    """traj, turn, role (system, query, observation, completion), text, tokens, up to MAX_TURNS model invocations.

    Only completions count as turns of the agent; what follows the last of them is never sent.
    """
    w = W.partitionBy("conv_id").orderBy("turn")
    said = F.sum(F.when(F.col("role") == "assistant", 1).otherwise(0)).over(w.rowsBetween(W.unboundedPreceding, -1))
    m = conversations.withColumn("said", F.coalesce(said, F.lit(0))).withColumn("n_user", F.sum(F.when(F.col("role") == "user", 1).otherwise(0)).over(w))
    role = F.when(F.col("role") == "system", "system").when(F.col("role") == "assistant", "completion").when(F.col("n_user") == 1, "query").otherwise("observation")
    return m.filter(F.col("said") < MAX_TURNS).select(F.col("conv_id").alias("traj"), "turn", role.alias("role"), F.coalesce("text", F.lit("")).alias("text"), usage(F.col("text")).alias("tokens"))


def rewrite_point(m: DataFrame) -> DataFrame:
    """Messages with `cut`: the turn of the first successful read of their trajectory (null if none).

    A read is an observation right after a completion of READ_CHARS characters or more.
    """
    w = W.partitionBy("traj").orderBy("turn")
    before_role, before_len = F.lag("role").over(w), F.lag(F.length("text")).over(w)
    read = (F.col("role") == "observation") & (before_role == "completion") & (before_len >= READ_CHARS)
    m = m.withColumn("read", read)
    return m.withColumn("cut", F.min(F.when(F.col("read"), F.col("turn"))).over(W.partitionBy("traj")))


def seed(m: DataFrame) -> DataFrame:
    """traj, seed text at the rewrite point: read paths, the latest read in full, the start of the latest completion."""
    cut = F.col("turn") <= F.col("cut")
    g = m.filter(cut).groupBy("traj").agg(
        F.array_sort(F.collect_set(F.when(F.col("read"), F.concat(F.lit("turn/"), F.col("turn").cast("string"))))).alias("paths"),
        F.max_by("text", F.when(F.col("read"), F.col("turn"))).alias("latest"),
        F.substring(F.max_by("text", F.when((F.col("role") == "completion") & (F.col("text") != ""), F.col("turn"))), 1, SEED_CHARS).alias("said"),
    )
    return g.select("traj", F.concat_ws("\n", F.concat_ws(" ", "paths"), "latest", "said").alias("seed"))


def replay_tokens(conversations: DataFrame, candidates: DataFrame | None = None) -> DataFrame:
    """traj, policy, invocations, tokens.  candidates: traj, tokens of the block that eager and compact carry."""
    m = rewrite_point(messages(conversations))
    s = seed(m).select("traj", usage(F.col("seed")).alias("seed_tokens"))
    m = m.join(s, "traj", "left")
    c = candidates.select("traj", F.col("tokens").alias("block")) if candidates is not None else None
    m = m.join(c, "traj", "left") if c is not None else m.withColumn("block", F.lit(0))
    w = W.partitionBy("traj").orderBy("turn").rowsBetween(W.unboundedPreceding, -1)
    fixed = F.sum(F.when(F.col("role").isin("system", "query"), F.col("tokens")).otherwise(0)).over(w)
    grown = F.sum(F.when(F.col("role").isin("system", "query"), 0).otherwise(F.col("tokens"))).over(w)
    after = F.sum(F.when(~F.col("role").isin("system", "query") & (F.col("turn") > F.col("cut")), F.col("tokens")).otherwise(0)).over(w)
    m = m.withColumn("fixed", F.coalesce(fixed, F.lit(0))).withColumn("grown", F.coalesce(grown, F.lit(0))).withColumn("after", F.coalesce(after, F.lit(0)))
    calls = m.filter("role = 'completion'").withColumn("policy", F.explode(F.array(*map(F.lit, POLICIES))))
    block = F.coalesce("block", F.lit(0))
    plain = F.col("fixed") + F.col("grown")
    rewritten = F.coalesce(F.col("turn") > F.col("cut"), F.lit(False))
    prompt = F.when(F.col("policy") == "grep", plain).when((F.col("policy") == "compact") & rewritten, F.col("fixed") + F.col("seed_tokens") + F.col("after")).otherwise(plain + block)
    return calls.groupBy("traj", "policy").agg(F.count("*").alias("invocations"), F.sum(prompt + F.col("tokens")).alias("tokens"))


ANSWER_SPANS = 5


def scripted(ranked: DataFrame, queries: DataFrame, agents: DataFrame) -> DataFrame:
    """Trajectories of scripted agents: query_id, repo, lang, kind, agent, policy, k, turns, tokens_used, spans.

    ranked: query_id, list (grep or candidates), rank, tokens, hit, path, start, end; queries:
    query_id, repo, lang, kind, tokens (system and query); agents: agent, budget, k.  A turn reads
    the next block; the agent stops at the target or at its budget and commits what it read, then
    (eager and compact) its unread candidates.  Block r is sent again in every later turn, so
    the tokens of a trajectory are one weighted sum over its blocks.
    """
    arms = queries.crossJoin(F.broadcast(agents)).withColumn("policy", F.explode(F.array(*map(F.lit, POLICIES))))
    per = ranked.groupBy("query_id", "list").agg(F.array_sort(F.collect_list(F.struct("rank", "tokens", "hit", "path", "start", "end"))).alias("bs"))
    which = F.when(F.col("policy") == "grep", "grep").otherwise("candidates")
    a = arms.withColumn("list", which).join(per, ["query_id", "list"], "left")
    most = F.least("budget", F.coalesce(F.size("bs"), F.lit(0)), F.lit(MAX_TURNS))
    most = F.greatest(most, F.lit(0))
    first = F.array_position(F.transform(F.slice("bs", 1, most), lambda b: b["hit"]), True)
    a = a.withColumn("turns", F.when(first > 0, first).otherwise(most).cast("int"))
    zero = F.lit(0).cast("bigint")
    block = F.when(F.col("policy") == "grep", zero).otherwise(F.coalesce(F.aggregate(F.slice("bs", 1, F.col("k")), zero, lambda s, b: s + b["tokens"]), zero))
    read = F.slice("bs", 1, F.col("turns"))
    sent = lambda x: F.coalesce(F.aggregate(x, zero, lambda s, b: s + (b["tokens"] + COMPLETION) * (F.col("turns") + 1 - b["rank"])), zero)
    calls, latest = F.col("turns") + 1, F.coalesce(F.try_element_at("bs", F.lit(1))["tokens"], zero)
    plain = calls * block + sent(read)
    compact = block + F.col("turns") * latest + sent(F.filter(read, lambda b: b["rank"] > 1))
    total = calls * (F.col("tokens") + COMPLETION) + F.when(F.col("policy") == "compact", compact).otherwise(plain)
    n = F.when(F.col("policy") == "grep", F.col("turns")).otherwise(F.greatest("turns", "k"))
    spans = F.transform(F.slice("bs", 1, n), lambda b: F.struct(b["path"].alias("path"), b["start"].alias("start"), b["end"].alias("end")))
    return a.select("query_id", "repo", "lang", "kind", "agent", "policy", "k", "turns", total.alias("tokens_used"), spans.alias("spans"))


def answer_recall(trajectories: DataFrame, targets: DataFrame, k: int = ANSWER_SPANS) -> DataFrame:
    """trajectories with `recall`: the share of a query's targets (query_id, path, start, end) that overlap one of
    the first k distinct spans it committed; an answer without spans is invalid and scores 0."""
    by = ["query_id", "agent", "policy", "k"]
    said = trajectories.select(*by, F.posexplode(F.slice(F.array_distinct("spans"), 1, k)).alias("at", "s")).select(*by, "s.path", "s.start", "s.end")
    t = targets.select("query_id", F.col("path").alias("tp"), F.col("start").alias("ts"), F.col("end").alias("te"))
    over = (F.col("path") == F.col("tp")) & (F.col("start") <= F.col("te")) & (F.col("ts") <= F.col("end"))
    hit = said.join(t, "query_id").filter(over).select(*by, "tp", "ts", "te").distinct().groupBy(*by).agg(F.count("*").alias("hit"))
    need = t.distinct().groupBy("query_id").agg(F.count("*").alias("need"))
    j = trajectories.join(need, "query_id", "left").join(hit, by, "left")
    return j.withColumn("recall", F.coalesce(F.col("hit") / F.col("need"), F.lit(0.0))).drop("hit", "need")


def slices(t: DataFrame) -> DataFrame:
    """policy, lang, kind, n, tokens, recall and the changes against grep, pooled over agents: overall, by language, by kind."""
    m = t.cube("policy", "lang", "kind").agg(F.grouping_id().alias("g"), F.count("*").alias("n"), F.avg("tokens_used").alias("tokens"), F.avg("recall").alias("recall"))
    m = m.filter(F.col("g").isin(1, 2, 3)).select("policy", F.coalesce("lang", F.lit("all")).alias("lang"), F.coalesce("kind", F.lit("all")).alias("kind"), "n", "tokens", "recall")
    base = m.filter("policy = 'grep'").select("lang", "kind", F.col("tokens").alias("t0"), F.col("recall").alias("r0"))
    return m.join(base, ["lang", "kind"]).select("policy", "lang", "kind", "n", F.round("tokens", 6).alias("tokens"), F.round("recall", 6).alias("recall"), F.round(F.col("recall") - F.col("r0"), 6).alias("delta"), F.round(F.col("tokens") / F.col("t0"), 6).alias("ratio"))


def policy_effects(t: DataFrame) -> DataFrame:
    """agent, policy, tokens, recall, and the paired change and token ratio against grep."""
    m = t.groupBy("agent", "policy").agg(F.avg("tokens_used").alias("tokens"), F.avg("recall").alias("recall"))
    base = m.filter("policy = 'grep'").select("agent", F.col("tokens").alias("t0"), F.col("recall").alias("r0"))
    return m.join(base, "agent").select("agent", "policy", F.round("tokens", 6).alias("tokens"), F.round("recall", 6).alias("recall"), F.round(F.col("recall") - F.col("r0"), 6).alias("delta"), F.round(F.col("tokens") / F.col("t0"), 6).alias("ratio"))


def select_policy(effects: DataFrame, margin: float = 0.05) -> DataFrame:
    """agent, policy with the fewest tokens among those whose lower bound keeps the margin (rows need `lower`)."""
    return effects.filter(F.col("lower") >= -margin).groupBy("agent").agg(F.min_by("policy", F.struct("tokens", "policy")).alias("policy"))
