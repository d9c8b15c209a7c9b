"""Mixing sources to target weights by iterative proportional fitting.

Token counts of the cells (source, language, topic) are raked until the marginals of all three attributes meet their targets;
a cell's factor is its fitted weight over its tokens. Documents are then drawn with probability min(1, scale * factor), the
scale such that the expected tokens are the budget; what a capped cell lacks is in the column `weight`, so weighted tokens of
the sample meet the targets in expectation. A draw depends on the id and the seed alone. Targets that no weights can meet
(an attribute's value may occur only where another's target says otherwise) leave a miss, told in `target_miss` and by a
warning.

Tokens are counted by a public tokenizer. A topic is the nearest of `TOPICS` centres of token profiles, fitted by k-means on
all texts; pass a column of your own to the operators to use another. Only each task's sums of profiles and the cells, at most
the product of the three domains, reach the driver; the number of cells is checked.

Defined cases: a null attribute is a value of its own, `(none)`; null or empty text has no tokens, topic `empty` and
probability 0; texts of any length are read whole; a null id draws like any other id; repeated rows are drawn alike; a table
without tokens keeps nothing; an empty table gives no rows; values absent from a given target have target 0; names that clash
are told apart by fresh().
"""

from __future__ import annotations

import warnings

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from quotaknn.llm.common import col, encoder, fresh, hash_rows, materialise, release, tokenizer_path

MOST_CELLS, BROADCAST_CELLS = 2_000_000, 200_000
TOPICS, ROUNDS, BUCKETS = 8, 25, 256
#: A profile is stored in whole numbers of this part.
UNIT = 65_535
#: A miss of a marginal share above this is told.
MISS = 1e-6


def profile(ids: np.ndarray) -> np.ndarray:
    """How often the token ids of a text fall into each of `BUCKETS` classes, square roots, of length 1."""
    at = (hash_rows(ids.astype(np.uint64)) % np.uint64(BUCKETS)).astype(np.int64)
    x = np.sqrt(np.bincount(at, minlength=BUCKETS))
    return x / max(np.linalg.norm(x), 1e-12)


def means(rows: DataFrame, profile_: Column, middle: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Sums and numbers of the profiles by their nearest centre; without centres, their sum, number and products in one row.
    Whole numbers are summed, so that neither the order nor the files of the table matter."""

    def run(batches):
        import pyarrow as pa

        sums = None
        for x in (unpacked(b.column(0).slice(i, 2_048).drop_null()) for b in batches for i in range(0, b.num_rows, 2_048)):
            if not len(x):
                continue
            if middle is None:
                own = np.vstack([x.sum(0), x.T @ x])
                counts = np.array([len(x)])
            else:
                of = (x @ middle.T).argmax(1)
                hot = np.zeros((len(middle), len(x)))
                hot[of, np.arange(len(x))] = 1
                own, counts = hot @ x, np.bincount(of, minlength=len(middle))
            # sums of whole numbers below 2^53 are exact
            sums = (own.astype(np.int64), counts) if sums is None else (sums[0] + own.astype(np.int64), sums[1] + counts)
        if sums is not None:
            yield pa.RecordBatch.from_arrays([pa.array([sums[0].tobytes()], pa.binary()), pa.array([sums[1].astype(np.int64).tobytes()], pa.binary())], names=["sums", "counts"])

    def added(batches):
        import pyarrow as pa

        own = None
        for b in batches:
            for pair in zip(*[[np.frombuffer(v, np.int64) for v in c.to_pylist()] for c in b.columns]):
                own = pair if own is None else [x + y for x, y in zip(own, pair)]
        if own is not None:
            yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in own], names=["sums", "counts"])

    schema = "sums binary, counts binary"
    few = rows.select(profile_).mapInArrow(run, schema).repartition(4).mapInArrow(added, schema)
    found = [[np.frombuffer(bytes(v), np.int64) for v in r] for r in few.collect()]
    if not found:
        return np.zeros((0, BUCKETS), np.int64), np.zeros(0, np.int64)
    return sum(r[0] for r in found).reshape(-1, BUCKETS), sum(r[1] for r in found)


def fit_topics(rows: DataFrame, profile_: Column, topics: int = TOPICS, rounds: int = ROUNDS) -> np.ndarray:
    """k-means centres (rows of length 1) of the profiles of all texts, each row counted. The start lies on both sides of the
    mean along the axes in which all profiles differ most; rounds go on until no centre moves, `rounds` at most."""
    sums, n = means(rows, profile_)
    if not len(sums):
        return np.zeros((0, BUCKETS))
    mean = sums[0] / n[0]
    spread, axes = np.linalg.eigh(sums[1:] / n[0] - np.outer(mean, mean))
    axes = axes * np.sign(axes[np.abs(axes).argmax(0), np.arange(BUCKETS)])
    number = int(min(topics, n[0]))
    c = np.repeat(mean[None, :], number, 0)
    for i in range((number - 1).bit_length()):
        side = ((np.arange(number) >> i) & 1) * 2.0 - 1
        c = c + side[:, None] * np.sqrt(max(spread[-1 - i], 0.0)) * axes[:, -1 - i]
    c = c / np.maximum(np.linalg.norm(c, axis=1, keepdims=True), 1e-12)
    for _ in range(rounds):
        sums, n = means(rows, profile_, c)
        size = np.linalg.norm(sums, axis=1, keepdims=True)
        new = np.where(size > 0, sums / np.maximum(size, 1e-12), c)
        still, c = np.abs(new - c).max() < 1e-3, new
        if still:
            break
    return c


def read_texts(tokenizer: str):
    """An Arrow function from a text column to struct<n_tokens, profile>; no profile where there are no tokens."""

    @F.arrow_udf("struct<n_tokens:long,profile:binary>")
    def read(texts):
        import pyarrow as pa

        n, made = [], []
        for ids in encoder(tokenizer, 0)(texts):
            n.append(len(ids) - 1)
            made.append(np.rint(profile(ids[:-1]) * UNIT).astype("<u2").tobytes() if len(ids) > 1 else None)
        release()
        return pa.StructArray.from_arrays([pa.array(n, pa.int64()), pa.array(made, pa.binary())], names=["n_tokens", "profile"])

    return read


def unpacked(column) -> np.ndarray:
    """Profiles in whole numbers, as rows of floats."""
    ends, data = column.buffers()[1:] if len(column) else (None, None)
    if ends is None:
        return np.zeros((0, BUCKETS))
    first = int(np.frombuffer(ends, np.int32)[column.offset])
    return np.frombuffer(data, "<u2", len(column) * BUCKETS, first).reshape(-1, BUCKETS).astype(float)


def topic_of(middle: np.ndarray):
    """An Arrow function from profiles to the names of their nearest centres."""

    @F.arrow_udf("string")
    def name(profiles):
        import pyarrow as pa

        filled = profiles.is_valid().to_numpy(zero_copy_only=False)
        out = np.full(len(profiles), "empty", object)
        if filled.any() and len(middle):
            out[filled] = [f"t{i}" for i in (unpacked(profiles.drop_null()) @ middle.T).argmax(1).tolist()]
        return pa.array(out.tolist(), pa.string())

    return name


def tempered(shares: dict, power: float) -> dict:
    """Targets proportional to share ** power: 1 leaves the shares, 0 makes them equal."""
    raised = {k: v**power for k, v in shares.items() if v > 0}
    total = sum(raised.values())
    return {k: v / total for k, v in raised.items()}


def rake(tokens: np.ndarray, groups: list[np.ndarray], targets: list[np.ndarray], tolerance: float = 1e-11) -> tuple[np.ndarray, float]:
    """Cell weights (shares of the whole) whose marginals meet the targets, and the largest miss left."""
    w = tokens / max(tokens.sum(), 1)
    miss = 0.0
    for _ in range(int(min(20_000, max(1_000, 1e8 // max(len(w), 1))))):
        miss = 0.0
        for g, t in zip(groups, targets):
            now = np.bincount(g, weights=w, minlength=len(t))
            miss = max(miss, float(np.abs(now - t).max()))
            w = w * np.divide(t, now, out=np.zeros_like(t), where=now > 0)[g]
        if miss < tolerance:
            break
    return w, miss


def scale_for(tokens: np.ndarray, factor: np.ndarray, budget: float) -> float:
    """The scale at which sum(tokens * min(1, scale * factor)) is the budget, or all that can be had."""
    live = factor > 0
    if not live.any() or budget <= 0:
        return 0.0
    t, f = tokens[live], factor[live]
    order = np.argsort(-f)
    t, f = t[order], f[order]
    capped = np.concatenate([[0], np.cumsum(t)])
    free = np.concatenate([np.cumsum((t * f)[::-1])[::-1], [0]])
    for i in range(len(f)):
        s = (budget - capped[i]) / free[i] if free[i] > 0 else np.inf
        if s * f[i] <= 1:
            return float(s)
    return float(1 / f.min())


def marginal_targets(cells: list[tuple], tokens: np.ndarray, targets: tuple, powers: tuple) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """For source, language and topic the value number of each cell, and the target shares by value number.

    Targets not given are tempered shares. A topic may follow from the language, so its default is the sum over languages of
    the language's target times the tempered share of the topic in it: both can then be met together."""
    groups, goals = [], []
    for k in range(3):
        values = sorted({c[k] for c in cells})
        number = {v: i for i, v in enumerate(values)}
        g = np.array([number[c[k]] for c in cells], int)
        own = np.bincount(g, weights=tokens, minlength=len(values)) if cells else np.zeros(0)
        if targets[k] is not None:
            goal = np.array([targets[k].get(v, 0.0) if o > 0 else 0.0 for v, o in zip(values, own)], float)
        elif k < 2:
            share = tempered(dict(zip(values, own / max(own.sum(), 1))), powers[k])
            goal = np.array([share.get(v, 0.0) for v in values], float)
        else:
            joint = np.zeros((len(goals[1]), len(values)))
            np.add.at(joint, (groups[1], g), tokens)
            live = joint > 0
            raised = np.where(live, np.divide(joint, joint.sum(1, keepdims=True), where=live, out=np.ones_like(joint)) ** powers[k], 0.0)
            goal = goals[1] @ np.divide(raised, raised.sum(1, keepdims=True), where=raised.sum(1, keepdims=True) > 0, out=np.zeros_like(raised))
        groups.append(g)
        goals.append(goal / max(goal.sum(), 1e-300))
    return groups, goals


def mix(docs: DataFrame, share: float = 0.5, powers: tuple = (0.0, 0.5, 0.5), targets: tuple = (None, None, None), seed: int = 7,
        doc_id: str = "doc_id", text: str = "text", source: str = "source", lang: str = "lang", topics: Column | None = None,
        tokenizer: str | None = None, keep_text: bool = True) -> DataFrame:
    """All rows and columns (without the text, if it is not to be kept) and, last, a struct named by fresh(docs, "mixed"):
    source, lang, topic, n_tokens, probability, weight, kept, target_miss. `share` is the expected share of all tokens;
    `targets` are shares by value, else tempered by `powers`."""
    spark = docs.sparkSession
    tokenizer = tokenizer or tokenizer_path("word_bpe_49k.json")
    facts, read = fresh(docs, "mixed"), fresh(docs, "read")
    own = read_texts(tokenizer)(F.coalesce(col(text), F.lit("")))
    name = lambda c: F.coalesce(c.cast("string"), F.lit("(none)"))
    rows = docs.withColumn(read, own)
    columns = [c for c in docs.columns if keep_text or c != text]
    given = F.lit(None).cast("string") if topics is None else name(topics)
    made = F.struct(name(col(source)).alias("source"), name(col(lang)).alias("lang"), given.alias("topic"), col(read)["n_tokens"].alias("n_tokens"))
    kept = [*[col(c) for c in columns], made.alias(facts)]
    # texts are tokenised once: the fit, the cells and the draw all read this table
    rows = materialise(rows.select(*kept, *([col(read)["profile"].alias(read)] if topics is None else [])), "mixed")
    if topics is None:
        middle = fit_topics(rows, col(read))
        rows = rows.withColumn(read, topic_of(middle)(col(read)))
        rows = rows.withColumn(facts, F.struct(*[col(facts)[c].alias(c) for c in ("source", "lang")], col(read).alias("topic"), col(facts)["n_tokens"].alias("n_tokens")))
        rows = rows.drop(read)
    summed = rows.groupBy(F.col(f"{facts}.source").alias("s"), F.col(f"{facts}.lang").alias("l"), F.col(f"{facts}.topic").alias("t")).agg(F.sum(f"{facts}.n_tokens").alias("tokens"))
    cells = summed.orderBy("s", "l", "t").limit(MOST_CELLS + 1).collect()
    if len(cells) > MOST_CELLS:
        raise ValueError(f"more than {MOST_CELLS} combinations of source, language and topic; coarsen one of them")
    tokens = np.array([c["tokens"] for c in cells], float)
    groups, goals = marginal_targets([(c["s"], c["l"], c["t"]) for c in cells], tokens, targets, powers)
    fitted, miss = rake(tokens, groups, goals) if tokens.sum() else (tokens, 0.0)
    if miss > MISS:
        warnings.warn(f"targets of source, language and topic cannot be met together: a share is off by {miss:.2g}", stacklevel=2)
    factor = np.divide(fitted, tokens, out=np.zeros_like(tokens), where=tokens > 0)
    scale = scale_for(tokens, factor, share * tokens.sum())
    p = np.minimum(1.0, scale * factor)
    weight = np.divide(scale * factor, p, out=np.zeros_like(p), where=p > 0)
    table = spark.createDataFrame(
        [(c["s"], c["l"], c["t"], float(a), float(b)) for c, a, b in zip(cells, p, weight)], "s_ string, l_ string, t_ string, p_ double, w_ double"
    )
    m = F.col(facts)
    table = F.broadcast(table) if len(cells) <= BROADCAST_CELLS else table  # a checked size, and no shuffle of texts by hot cells
    joined = rows.join(table, (m["source"] == F.col("s_")) & (m["lang"] == F.col("l_")) & (m["topic"] == F.col("t_")), "left")
    p_row = F.when(m["n_tokens"] > 0, F.col("p_")).otherwise(F.lit(0.0))
    done = F.struct(
        m["source"].alias("source"), m["lang"].alias("lang"), m["topic"].alias("topic"), m["n_tokens"].alias("n_tokens"), p_row.alias("probability"),
        F.col("w_").alias("weight"), (draw(col(doc_id), seed) < p_row).alias("kept"), F.lit(float(miss)).alias("target_miss"),
    )
    return joined.withColumn(facts, done).select(*[col(c) for c in columns], facts)


def draw(doc_id: Column, seed: int) -> Column:
    """A number in [0, 1) that depends on the id and the seed alone."""
    return F.pmod(F.xxhash64(F.coalesce(doc_id.cast("string"), F.lit("(none)")), F.lit(seed)), F.lit(1 << 52)) / F.lit(float(1 << 52))


def sampled(docs: DataFrame, share: float = 0.5, **named) -> DataFrame:
    """The rows drawn; columns as they were."""
    drawn = mix(docs, share, **named)
    c = drawn.columns[-1]
    return drawn.where(F.col(c)["kept"]).drop(c)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "source", "lang")
    return mix(docs, keep_text=False).select("doc_id", "mixed.*")
