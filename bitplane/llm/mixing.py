"""Mixing sources to target weights by iterative proportional fitting (DataFrame functions only).

Documents fall into cells of source, language and topic.  A topic is the rarest of a few anchor words that a
document has; anchors are the corpus's most frequent words of middle length below the share of documents that
tells stop words, counted over all documents, unless the caller names a topic column.  Targets
are the caller's shares, or the corpus's own token shares raised to a power.  Raking scales the cells
in turn until their token weights meet the target share of every source, language
and topic; a document's probability is its cell's factor on a common scale, at
most one, set so that the wanted share of all tokens is expected.  Sampling
compares it to a number made from a digest of the id, so a document's fate does
not depend on the cluster, the order or other documents.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stored

MARGINS = ["source", "lang", "topic"]

#: Cells (about 100 bytes each) up to which raking runs in one partition without shuffles and the factor table is broadcast.
FEW_CELLS = 100_000


#: Fixed value: what parts words.
BLANKS = "[ \\t\\n\\r]+"


def words_of(text_col: str) -> Column:
    """Runs of characters other than space, tab and line ends; the first or last may be empty."""
    return F.split(F.coalesce(F.col(text_col), F.lit("")), BLANKS, -1)


def anchors(docs: DataFrame, topics: int, text_col: str = "text", most_share: float = 0.1, sizes: tuple[int, int] = (5, 7)) -> list[str]:
    """The anchor words, rarest first: at most ``topics`` of those in at most ``most_share`` of all documents."""
    held = F.array_distinct(F.filter(words_of(text_col), lambda w: F.char_length(w).between(*sizes)))
    counts = docs.select(F.explode(held).alias("word")).groupBy("word").agg(F.count(F.lit(1)).alias("n"))
    top = counts.where(F.col("n") <= F.lit(most_share * docs.count())).orderBy(F.desc("n"), "word").limit(topics).collect()
    return [r.word for r in reversed(top)]


def features(docs: DataFrame, anchor_words: list[str], text_col: str = "text", topic_col: str | None = None) -> DataFrame:
    """Adds __source, __lang, __topic and __tokens (words).

    A topic is the place (from 1) of the first anchor word in the text, 0 without any; with ``topic_col`` it is that
    column as a string, "(none)" for null.
    """
    words = words_of(text_col)
    empty = F.aggregate(F.array(F.get(words, F.lit(0)), F.get(words, F.size(words) - 1)), F.lit(0), lambda n, w: n + (w == "").cast("int"))
    tokens = F.when(F.size(words) == 1, F.size(words) - (F.get(words, F.lit(0)) == "").cast("int")).otherwise(F.size(words) - empty)
    if topic_col is not None:
        topic = F.coalesce(F.col(topic_col).cast("string"), F.lit("(none)"))
    elif anchor_words:
        known = F.array(*map(F.lit, anchor_words))
        topic = F.coalesce(F.array_position(known, F.get(F.array_intersect(known, words), F.lit(0))), F.lit(0)).cast("int")
    else:
        topic = F.lit(0)
    return docs.withColumns({
        "__source": F.coalesce(F.col("source").cast("string"), F.lit("(none)")),
        "__lang": F.coalesce(F.col("lang").cast("string"), F.lit("(none)")),
        "__topic": topic,
        "__tokens": tokens.cast("long"),
    })


def cells_of(tagged: DataFrame) -> DataFrame:
    return tagged.groupBy(*[F.col(f"__{m}").alias(m) for m in MARGINS]).agg(F.sum("__tokens").alias("tokens"))


def targets(cells: DataFrame, margin: str, wanted: float | dict) -> DataFrame:
    """Target shares of the margin's values that have tokens: the caller's (by value as a string), or token shares to a power.

    Shares are normalised; a value without a share gets none.
    """
    held = cells.groupBy(margin).agg(F.sum("tokens").alias("t")).where("t > 0")
    if isinstance(wanted, dict):
        rows = cells.sparkSession.createDataFrame([(str(k), float(v)) for k, v in wanted.items()], "value string, p double")
        sums = stored(held.join(rows, F.col(margin).cast("string") == F.col("value")).select(margin, "p"), f"shares-{margin}")
    else:
        sums = stored(held.withColumn("p", F.pow(F.col("t").cast("double"), F.lit(float(wanted)))), f"shares-{margin}")
    total = sums.agg(F.sum("p")).first()[0]
    return sums.select(margin, (F.col("p") / F.lit(total or 1.0)).alias("target"))


def rake(cells: DataFrame, wanted: dict[str, DataFrame], rounds: int) -> DataFrame:
    """Adds ``raked``: the cells' weights after so many rounds over all margins (sum one).

    A cell without tokens, or in a margin value without a target, gets zero.
    """
    total = cells.agg(F.sum("tokens")).first()[0]
    state = cells.select(*MARGINS, "tokens", (F.col("tokens") / F.lit(float(total or 1))).alias("raked"))
    few = cells.count() <= FEW_CELLS
    together = (lambda df: df.coalesce(1)) if few else (lambda df: df)
    wanted = {m: stored(together(t), f"target-{m}") for m, t in wanted.items()}
    for _ in range(rounds):
        state = together(state)
        for margin in MARGINS:
            now = state.groupBy(margin).agg(F.sum("raked").alias("now")).join(together(wanted[margin]), margin)
            factors = now.select(margin, F.coalesce(F.col("target") / F.nullif("now", F.lit(0.0)), F.lit(0.0)).alias("f"))
            state = state.join(factors, margin, "left").select(*MARGINS, "tokens", (F.col("raked") * F.coalesce("f", F.lit(0.0))).alias("raked"))
        state = stored(state, "raked")
    return state


def calibrate(raked: DataFrame, share: float, steps: int = 6) -> DataFrame:
    """Adds ``probability``: least of one and factor times scale, for the expected ``share`` of all tokens.

    The scale is a driver number found by a few sums over the cells.
    """
    cells = stored(raked.withColumn("factor", F.when(F.col("tokens") > 0, F.col("raked") / F.col("tokens")).otherwise(0.0)), "factors")
    scale = None
    for _ in range(steps):
        full = F.lit(False) if scale is None else F.col("factor") * scale >= 1
        got = cells.agg(
            F.sum("tokens").alias("all"), F.sum(F.when(full, F.col("tokens")).otherwise(0)).alias("full"), F.sum(F.when(full, 0.0).otherwise(F.col("factor") * F.col("tokens"))).alias("rest")
        ).first()
        left = share * (got["all"] or 0) - (got["full"] or 0)
        new = left / got["rest"] if got["rest"] else None
        if new is None or new <= 0 or new == scale:
            break
        scale = new
    return cells.withColumn("probability", F.round(F.least(F.lit(1.0), F.col("factor") * (scale or 0.0)), 6))


def uniform(id_col: Column, seed: str) -> Column:
    """A number in [0, 1) from the id's digest; a null id has one too."""
    digest = F.sha2(F.concat(F.lit(f"{seed}:"), F.coalesce(id_col.cast("string"), F.lit("null"))), 256)
    return F.conv(F.substring(digest, 1, 12), 16, 10).cast("long") / F.lit(float(1 << 48))


#: Powers of the token shares that are the targets where the caller names none.
POWERS = {"source": 0.5, "lang": 0.7, "topic": 0.5}


def weigh(docs: DataFrame, share: float = 0.7, wanted: dict[str, float | dict] | None = None, topics: int = 8, rounds: int = 8, seed: str = "mix", id_col: str = "doc_id", topic_col: str | None = None) -> DataFrame:
    """All columns of ``docs`` with __source, __lang, __topic, __tokens, __probability and __selected.

    ``wanted`` gives each margin's target shares by value, or a power of its token shares.
    Null sources and languages are values of their own ("(none)").  Documents
    without words weigh nothing and are not selected.  Rows that repeat an id share its
    number, and so its fate within a cell.
    """
    words = [] if topic_col is not None else anchors(docs, topics)
    tagged = features(docs, words, topic_col=topic_col)
    cells = stored(cells_of(tagged), "cells")
    wanted = {m: targets(cells, m, (POWERS | (wanted or {}))[m]) for m in MARGINS}
    final = stored(calibrate(rake(cells, wanted, rounds), share), "cell-probabilities")
    table = final.select(*[F.col(m).alias(f"__{m}") for m in MARGINS], F.col("probability").alias("__probability"))
    if final.count() <= FEW_CELLS:
        table = F.broadcast(table)
    out = tagged.join(table, [f"__{m}" for m in MARGINS], "left")
    return out.withColumn("__selected", uniform(F.col(id_col), seed) < F.coalesce("__probability", F.lit(0.0)))


def mix(docs: DataFrame, **how) -> DataFrame:
    """The sampled documents with their own columns."""
    return weigh(docs, **how).where("__selected").select(*[F.col(f"`{c}`") for c in docs.columns])
