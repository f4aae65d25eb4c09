"""A count-based conditional token model: real log-probabilities without a network.

p(token | position, context) with add-alpha smoothing, the context being the preceding token
(order 1) or nothing (order 0). Used for cross-entropy, importance ratios and ablations.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from navspark.session import bounded, kept


def token_rows(seqs: DataFrame, key: str, tokens: str = "tokens", keep: tuple[str, ...] = ()) -> DataFrame:
    """(key, pos, token, ctx): ctx is the token before, or the mark of the start."""
    t = F.col(tokens)
    return seqs.select(key, *keep, F.posexplode(t).alias("pos", "token"), t.alias("_t")).withColumn(
        "ctx", F.when(F.col("pos") == 0, F.lit("<s>")).otherwise(F.get("_t", F.col("pos") - 1))
    ).drop("_t")


def fit_token_lm(rows: DataFrame, group: tuple[str, ...] = ("pos",)) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Counts of (group, ctx, token) and (group, ctx), and the vocabulary size of each group; counted once."""
    pair = kept(rows.groupBy(*group, "ctx", "token").agg(F.count("*").alias("n")))
    ctx = pair.groupBy(*group, "ctx").agg(F.sum("n").alias("n_ctx"))
    vocab = pair.select(*group, "token").distinct().groupBy(*group).agg(F.count("*").alias("n_vocab"))
    return pair, ctx, vocab


def log_prob(n: Column, n_ctx: Column, n_vocab: Column, alpha: float = 1.0) -> Column:
    return F.log((F.coalesce(n, F.lit(0)) + alpha) / (F.coalesce(n_ctx, F.lit(0)) + alpha * (F.coalesce(n_vocab, F.lit(0)) + 1)))


def score(rows: DataFrame, model: tuple[DataFrame, DataFrame, DataFrame], group: tuple[str, ...] = ("pos",), alpha: float = 1.0, name: str = "logp") -> DataFrame:
    """``rows`` with the log-probability of each token; unseen tokens share one extra slot.

    Tokens are as skewed as keys come, so they are not shuffled while the model's tables, once
    counted, can be broadcast.
    """
    pair, ctx, vocab = map(bounded, model)
    on = list(group)
    j = rows.join(pair, [*on, "ctx", "token"], "left").join(ctx, [*on, "ctx"], "left").join(vocab, on, "left")
    return j.withColumn(name, log_prob(F.col("n"), F.col("n_ctx"), F.col("n_vocab"), alpha)).drop("n", "n_ctx", "n_vocab")


def ce_loss(scored: DataFrame, by: tuple[str, ...] = (), mask: Column | None = None, logp: str = "logp") -> DataFrame:
    """Summed and mean negative log-probability over supervised positions."""
    mask = F.lit(True) if mask is None else mask
    loss = F.sum(F.when(mask, -F.col(logp)))
    n = F.sum(mask.cast("long"))
    return scored.groupBy(*by).agg(n.alias("n_tok"), loss.alias("loss_sum"), (loss / n).alias("ce"))


def kl_exact(p: DataFrame, q: DataFrame, ctx_weight: DataFrame, group: tuple[str, ...]) -> DataFrame:
    """Sum over the vocabulary of p (log p - log q) for each context, weighted by its share.

    p and q: (group, ctx, token, logp) on the same support.
    """
    on = [*group, "ctx", "token"]
    j = p.select(*on, F.col("logp").alias("lp")).join(q.select(*on, F.col("logp").alias("lq")), on)
    per = j.groupBy(*group, "ctx").agg(F.sum(F.exp("lp") * (F.col("lp") - F.col("lq"))).alias("kl"))
    w = ctx_weight.crossJoin(F.broadcast(ctx_weight.agg(F.sum("n_ctx").alias("_s"))))
    return per.join(w, [*group, "ctx"]).agg(F.sum(F.col("kl") * F.col("n_ctx") / F.col("_s")).alias("kl"))
