"""Language-model scores by context-tree weighting over bytes, beside a word-unigram base.

A byte is eight binary decisions; each decision has a Krichevsky-Trofimov estimate at every depth
of its context tree (from no to ``DEPTH`` previous bytes), and the weighted probability halves
between a node's own estimate and the product of its children's. KT block probabilities don't
depend on order, so one aggregation of byte strings over all training texts gives every count.
A context is a node from ``LEAST`` training symbols on, at every size of the corpus, so the tree
grows with it; rarer contexts are one child, "other", of their suffix, which unseen ones join.
A text starts after line feeds and ends with the byte 255, which UTF-8 never uses.

The tree is never in one place. Strings whose nearest ``STEM`` context bytes agree share a shard;
shards weigh their subtrees, the driver joins their roots (at most 256 ** ``STEM`` contexts), and
shards turn what comes back into a log probability for every string of the corpus, held-out ones
included. The ``HOT_CODES`` most frequent are broadcast; the rest of a text's strings travel as
packed blocks to the partition that holds their values, and only sums per text come back.

The base needs the training count of every word, and words travel likewise: those of at least a
``HOT_SHARE``-th of all tokens are at most that many, and are broadcast.

Defined results: null text is empty and has one token, the end; a null id is held out; repeated
rows count and score each; texts are read whole, in slices, and one of any length is a slice of
its own; with nothing to learn from, every bit has probability one half and the base score is
minus infinity; other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bucketseed.llm.hashing import mix, pieces, word_hashes
from bucketseed.llm.labelled import crc_fold
from bucketseed.staging import staged

DEPTH = 5
LEAST = 2
STEM = 2
HOT_CODES = 1 << 20
#: Distinct strings to a shard of the tree, but for a stem that alone has more.
SHARD_CODES = 200_000
HOT_SHARE = 100_000
PART_TOKENS = 8_000_000
PART_CODES = 1_000_000
END = np.uint64(0x0123456789ABCDEF)
#: Distinct words that a counting task holds before it hands them on.
HELD = 1_500_000


def symbols(data: np.ndarray, offs: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """Codes of all bytes and ends with ``depth`` bytes before them, and texts' beginnings.

    The lowest byte of a code is the symbol, the next one the byte before it, and so on.
    """
    lens = np.diff(offs)
    texts, n = len(lens), int(offs[-1])
    line = np.full(n + (depth + 1) * texts, 10, np.uint64)
    line[np.arange(n) + np.repeat(np.arange(texts) * (depth + 1) + depth, lens)] = data
    begin = offs[:-1] + (depth + 1) * np.arange(texts)
    line[begin + lens + depth] = 255
    code = np.zeros(len(line) - depth, np.uint64)
    for back in range(depth + 1):
        code |= line[depth - back : len(line) - back] << np.uint64(8 * back)
    real = np.ones(len(code), bool)
    for k in range(1, depth + 1):
        real[begin[1:] - k] = False
    return code[real], offs[:-1] + np.arange(texts)


def _log_gamma(x: np.ndarray) -> np.ndarray:
    shifted = x + 8
    rising = np.log(x)
    for k in range(1, 8):
        rising = rising + np.log(x + k)
    inverse = 1 / shifted
    tail = inverse * (1 / 12 - inverse**2 * (1 / 360 - inverse**2 / 1260))
    return (shifted - 0.5) * np.log(shifted) - shifted + 0.5 * np.log(2 * np.pi) + tail - rising


def log_kt(zeros: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """Log of the KT block probability of so many zeros and ones."""
    return (
        _log_gamma(zeros + 0.5) + _log_gamma(ones + 0.5) - _log_gamma(zeros + ones + 1.0) - np.log(np.pi)
    )


def _kt(zeros: np.ndarray, ones: np.ndarray) -> np.ndarray:
    return (ones + 0.5) / (zeros + ones + 1.0)


class Forest:
    """Subtrees of the 255 binary context trees, from their leaves at depth ``hi`` to depth ``lo``.

    A key holds the bits decided before, then the context bytes, nearest first; keys are sorted and
    distinct. ``deep`` is the depth to which a key's context is made of nodes; ``weights`` are the
    leaves' weighted log probabilities, their own estimates if not given.
    """

    def __init__(self, keys, zeros, ones, deep, hi: int, lo: int, weights=None):
        self.leaf = _kt(zeros, ones)
        weights = log_kt(zeros, ones) if weights is None else weights
        self.steps = []
        for d in range(hi - 1, lo - 1, -1):
            alive = deep > d
            keys = keys >> np.uint64(8)
            fresh = np.ones(len(keys), bool)
            fresh[1:] = keys[1:] != keys[:-1]
            first, up = np.flatnonzero(fresh), np.cumsum(fresh) - 1
            rest = [_runs(np.where(alive, 0.0, n), first) for n in (zeros, ones)]
            parts = _runs(np.where(alive, weights, 0.0), first) + log_kt(*rest)
            zeros, ones, keys, deep = _runs(zeros, first), _runs(ones, first), keys[first], deep[first]
            own = log_kt(zeros, ones)
            both = np.logaddexp(own, parts)
            self.steps.append((up, alive, np.exp(own - both), _kt(zeros, ones), _kt(*rest)))
            weights = both + np.log(0.5)
        self.keys, self.zeros, self.ones, self.weights = keys, zeros, ones, weights

    def settle(self, fixed: np.ndarray, left: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Leaves' settled probabilities of a one and open shares, from those at the roots."""
        for up, alive, share, own, rest in reversed(self.steps):
            fixed = fixed + left * share * own
            left = left * (1 - share)
            fixed, left = np.where(alive, fixed[up], (fixed + left * rest)[up]), np.where(alive, left[up], 0.0)
        return fixed, left


def _runs(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    return np.add.reduceat(values, first) if len(first) else values


def plant(codes: np.ndarray, n: np.ndarray, depth: int, stem: int, least: int) -> tuple[Forest, np.ndarray]:
    """The trees below ``stem`` of strings and their counts, and each string's eight leaves."""
    back = np.zeros(len(codes), np.uint64)
    for k in range(1, depth + 1):
        back |= (codes >> np.uint64(8 * k) & np.uint64(255)) << np.uint64(8 * (depth - k))
    order = np.argsort(back)
    sorted_, deep = back[order], np.full(len(codes), stem - 1)
    for d in range(stem, depth + 1):
        prefix = sorted_ >> np.uint64(8 * (depth - d))
        fresh = np.ones(len(prefix), bool)
        fresh[1:] = prefix[1:] != prefix[:-1]
        deep[order] += (_runs(n[order], np.flatnonzero(fresh)) >= least)[np.cumsum(fresh) - 1]
    byte = (codes & np.uint64(255)) | np.uint64(256)
    keys = np.concatenate([(byte >> np.uint64(8 - j)) << np.uint64(8 * depth) | back for j in range(8)])
    bit = _bits(codes)
    keys, leaf = np.unique(keys, return_inverse=True)
    size = np.tile(n, 8).astype(float)
    zeros, ones = (np.bincount(leaf, np.where(bit == b, size, 0.0), len(keys)) for b in (0, 1))
    reach = np.zeros(len(keys), np.int64)
    reach[leaf] = np.tile(deep, 8)
    return Forest(keys, zeros, ones, reach, depth, stem), leaf


def _bits(codes: np.ndarray) -> np.ndarray:
    return np.concatenate([(codes >> np.uint64(7 - j)) & np.uint64(1) for j in range(8)])


def joined(keys, zeros, ones, weights, stem: int, least: int) -> tuple[np.ndarray, np.ndarray]:
    """Settled probabilities and open shares at the shards' roots, from their counts and weights."""
    whole = keys >> np.uint64(8 * stem) == 1
    context = (keys & np.uint64((1 << (8 * stem)) - 1)).astype(np.int64)
    deep = np.zeros(len(keys), np.int64)
    for d in range(1, stem + 1):
        nearest = context >> (8 * (stem - d))
        deep += (np.bincount(nearest[whole], (zeros + ones)[whole], 256**d) >= least)[nearest]
    top = Forest(keys, zeros, ones, deep, stem, 0, weights)
    return top.settle(np.zeros(len(top.keys)), np.ones(len(top.keys)))


def _column(table: pa.Table, name: str, kind) -> np.ndarray:
    return np.concatenate([np.zeros(0, kind), *(np.frombuffer(x, kind) for x in table[name].to_pylist())])


def predictions(grams: DataFrame, distinct: int, parts: int, depth: int, least: int, shard_codes: int) -> DataFrame:
    """(part, key, n, v): the log10 probability of each string of (key, n), and where it is looked up."""
    spark, stem = grams.sparkSession, min(STEM, depth)
    near = F.shiftright("key", 8).bitwiseAND(F.lit((1 << (8 * stem)) - 1))
    shards = grams.select(F.pmod(F.hash(near), F.lit(distinct // shard_codes + 1)).alias("shard"), "key", "n")

    def planted(table: pa.Table):
        codes = table["key"].to_numpy().view(np.uint64)
        return codes, *plant(codes, table["n"].to_numpy(), depth, stem, least)

    def weigh(table: pa.Table) -> pa.Table:
        _, trees, _ = planted(table)
        parts = (trees.keys, trees.zeros, trees.ones, trees.weights)
        return pa.table([pa.array([x.tobytes()], pa.binary()) for x in parts], ["keys", "zeros", "ones", "weights"])

    roots = (
        shards.groupBy("shard")
        .applyInArrow(weigh, "keys binary, zeros binary, ones binary, weights binary")
        .toArrow()
    )
    keys = _column(roots, "keys", np.uint64)
    order = np.argsort(keys)
    zeros, ones, weights = (_column(roots, name, np.float64)[order] for name in ("zeros", "ones", "weights"))
    top = spark.sparkContext.broadcast((keys[order], *joined(keys[order], zeros, ones, weights, stem, least)))

    def settle(table: pa.Table) -> pa.Table:
        codes, trees, leaf = planted(table)
        keys, fixed, left = top.value
        at = np.searchsorted(keys, trees.keys)
        fixed, left = trees.settle(fixed[at], left[at])
        one = (fixed + left * trees.leaf)[leaf]
        logs = np.log10(np.where(_bits(codes) == 1, one, 1 - one)).reshape(8, len(codes)).sum(0)
        part = (mix(codes) % np.uint64(parts)).astype(np.int32)
        return pa.table({"part": part, "key": codes.view(np.int64), "n": table["n"], "v": logs})

    return shards.groupBy("shard").applyInArrow(settle, "part int, key bigint, n bigint, v double")


def frequent(grams: DataFrame, most: int) -> int:
    """The least count that at most ``most`` strings reach, to within an eighth of an octave."""
    step = F.ceil(F.log2("n") * 8).cast("int")
    total, least = 0, 1 << 62
    steps = grams.filter("n > 0").groupBy(step.alias("step")).agg(F.min("n").alias("least"), F.count("*").alias("c"))
    for row in sorted(steps.collect(), key=lambda r: -r["step"]):
        total += row["c"]
        if total > most:
            break
        least = row["least"]
    return least


class Held:
    """Counts by key that a task has not handed on yet."""

    def __init__(self):
        self.parts: list[tuple[np.ndarray, np.ndarray]] = []
        self.size = 0

    def add(self, keys: np.ndarray, counted: bool = True) -> None:
        found, n = np.unique(keys, return_counts=True)
        self.parts.append((found, n if counted else np.zeros_like(n)))
        self.size += len(found)

    def merge(self) -> None:
        if len(self.parts) > 1:
            found, at = np.unique(np.concatenate([p[0] for p in self.parts]), return_inverse=True)
            n = np.bincount(at, np.concatenate([p[1] for p in self.parts]), len(found)).astype(np.int64)
            self.parts, self.size = [(found, n)], len(found)

    def taken(self) -> tuple[np.ndarray, np.ndarray]:
        out = self.parts[0] if self.parts else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
        self.parts, self.size = [], 0
        return out


def corpus_counts(docs: DataFrame, depth: int = DEPTH) -> DataFrame:
    """(kind, key, n): training counts of byte strings of depth + 1 (0) and of word hashes (1).

    Strings of held-out texts alone count 0; words of theirs are not counted.
    """

    def run(batches):
        held = {0: Held(), 1: Held()}

        def rows(kind, k, n):
            for at in range(0, len(k), 100_000):
                part = slice(at, at + 100_000)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.full(len(k[part]), kind, np.int32)), pa.array(k[part].view(np.int64)), pa.array(n[part])],
                    ["kind", "key", "n"],
                )

        for batch, data, offs in pieces(batches):
            code, begin = symbols(data, offs, depth)
            words, first = word_hashes(data, offs)
            train = ~batch.column("held_out").to_numpy(zero_copy_only=False)
            learnt = np.repeat(train, np.diff(np.append(begin, len(code))))
            held[0].add(code[learnt])
            held[0].add(code[~learnt], counted=False)
            held[1].add(np.append(words[np.repeat(train, np.diff(first))], np.full(train.sum(), END)))
            for kind, own in held.items():
                if own.size > HELD:
                    own.merge()
                    if own.size > HELD // 2:
                        yield from rows(kind, *own.taken())
        for kind, own in held.items():
            own.merge()
            yield from rows(kind, *own.taken())

    return (
        docs.select("text", "held_out")
        .mapInArrow(run, "kind int, key bigint, n bigint")
        .groupBy("kind", "key")
        .agg(F.sum("n").alias("n"))
    )


def _found(own: np.ndarray, asked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of ``asked`` in sorted ``own``, and which are there."""
    if not len(own):
        return np.zeros(len(asked), np.int64), np.zeros(len(asked), bool)
    at = np.minimum(np.searchsorted(own, asked), len(own) - 1)
    return at, own[at] == asked


def context_tree_scores(
    docs: DataFrame,
    held_out: Column,
    text: str = "text",
    hot_share: int = HOT_SHARE,
    part_tokens: int = PART_TOKENS,
    depth: int = DEPTH,
    least: int = LEAST,
    hot_codes: int = HOT_CODES,
    shard_codes: int = SHARD_CODES,
) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, bits_per_byte)."""
    spark = docs.sparkSession
    rows = docs.select("doc_id", F.col(text).alias("text"), F.coalesce(held_out, F.lit(True)).alias("held_out"))
    counts = staged(corpus_counts(rows, depth), "counts")
    totals = {r["kind"]: r for r in counts.groupBy("kind").agg(F.sum("n").alias("n"), F.count("*").alias("v")).collect()}
    n_all, distinct = (int(totals[1][x] or 0) if 1 in totals else 0 for x in ("n", "v"))
    strings = int(totals[0]["v"]) if 0 in totals else 0
    rare = max(n_all // hot_share, 1)
    code_parts = strings // PART_CODES + 1
    logs = staged(
        predictions(counts.filter("kind = 0").select("key", "n"), strings, code_parts, depth, least, shard_codes),
        "predictions",
    )

    def sorted_pairs(table: DataFrame, value: str) -> tuple[np.ndarray, np.ndarray]:
        pairs = table.select("key", value).toArrow()
        keys = pairs["key"].to_numpy().astype(np.int64).view(np.uint64)
        order = np.argsort(keys)
        return keys[order], pairs[value].to_numpy()[order]

    # At most hot_codes strings and hot_share words are gathered, whatever the corpus.
    hot = sorted_pairs(logs.filter(F.col("n") >= frequent(logs, hot_codes)), "v")
    warm_words = sorted_pairs(counts.filter((F.col("kind") == 1) & (F.col("n") > rare)), "n")
    below = 0.1 * (distinct + 1) + n_all if n_all else np.inf
    known = spark.sparkContext.broadcast((*hot, *warm_words))
    parts = n_all // part_tokens + 1

    def run(batches):
        strings, values, keys, sizes = known.value
        block = TaskContext.get().partitionId() << 32
        names = ["block", "idx", "doc_id", "held_out", "n_tokens", "hot_known", "hot_sum", "score", "bytes", "part", "ids", "keys"]
        for batch, data, offs in pieces(batches):
            texts = len(offs) - 1
            code, begin = symbols(data, offs, depth)
            # Codes have 48 bits and a slice 65,536 texts at most, so one sort brings equal codes together.
            owners = np.repeat(np.arange(texts, dtype=np.uint64), np.diff(np.append(begin, len(code))))
            code = np.sort(code << np.uint64(16) | owners)
            owners = (code & np.uint64(0xFFFF)).astype(np.int64)
            code >>= np.uint64(16)
            fresh = np.ones(len(code), bool)
            fresh[1:] = code[1:] != code[:-1]
            one, times = code[fresh], np.diff(np.append(np.flatnonzero(fresh), len(code)))
            at, hot = _found(strings, one)
            score = np.bincount(owners, np.repeat(np.where(hot, values[at], 0.0) if len(values) else np.zeros(len(one)), times), texts)
            far = ~np.repeat(hot, times)
            words, first = word_hashes(data, offs)
            per = np.diff(first)
            text_of = np.concatenate([np.repeat(np.arange(texts), per), np.arange(texts)])
            words = np.concatenate([words, np.full(texts, END)])
            at, warm = _found(keys, words)
            logs = np.log10((sizes[at[warm]] + 0.1) / below) if warm.any() else np.zeros(0)
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(np.full(texts, block)),
                    pa.array(np.arange(texts, dtype=np.int32)),
                    batch.column("doc_id"),
                    batch.column("held_out"),
                    pa.array(per + 1),
                    pa.array(np.bincount(text_of[warm], minlength=texts)),
                    pa.array(np.bincount(text_of[warm], logs, texts).astype(float)),
                    pa.array(score),
                    pa.array(np.diff(offs)),
                    pa.nulls(texts, pa.int32()),
                    pa.nulls(texts, pa.binary()),
                    pa.nulls(texts, pa.binary()),
                ],
                names,
            )
            cold = np.concatenate([words[~warm], code[far]])
            owner = np.concatenate([text_of[~warm], owners[far]]).astype(np.uint32)
            part = np.concatenate(
                [words[~warm].view(np.int64) % parts, parts + (mix(code[far]) % np.uint64(code_parts)).astype(np.int64)]
            ).astype(np.int32)
            order = np.lexsort((owner, part))
            cold, owner, part = cold[order], owner[order], part[order]
            there, start = np.unique(part, return_index=True)
            stop = np.append(start[1:], len(part))
            m = len(there)
            if m:
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.full(m, block)),
                        pa.nulls(m, pa.int32()),
                        pa.nulls(m, batch.column("doc_id").type),
                        *[pa.nulls(m, t) for t in (pa.bool_(), pa.int64(), pa.int64(), pa.float64(), pa.float64(), pa.int64())],
                        pa.array(there),
                        pa.array([owner[a:b].tobytes() for a, b in zip(start, stop, strict=True)], pa.binary()),
                        pa.array([cold[a:b].tobytes() for a, b in zip(start, stop, strict=True)], pa.binary()),
                    ],
                    names,
                )
            block += 1

    id_type = dict(rows.dtypes)["doc_id"]
    passed = staged(
        rows.mapInArrow(
            run,
            f"block bigint, idx int, doc_id {id_type}, held_out boolean, n_tokens bigint, hot_known bigint, "
            "hot_sum double, score double, bytes bigint, part int, ids binary, keys binary",
        ),
        "scored",
    )

    def resolve(left: pa.Table, right: pa.Table) -> pa.Table:
        own = right["key"].to_numpy().astype(np.int64).view(np.uint64)
        order = np.argsort(own)
        own, values = own[order], right["v"].to_numpy()[order]
        out = []
        for part, block, ids, keys in zip(*(left[c].to_pylist() for c in ("part", "block", "ids", "keys")), strict=True):
            asked, owner = np.frombuffer(keys, np.uint64), np.frombuffer(ids, np.uint32)
            at, there = _found(own, asked)
            value = np.where(there, values[at], 0.0) if len(own) else np.zeros(len(asked))
            texts, where = np.unique(owner, return_inverse=True)
            nothing = np.zeros(len(texts))
            if part < parts:
                sums = (np.bincount(where, np.log10((value + 0.1) / below), len(texts)), np.bincount(where, value > 0, len(texts)), nothing)
            else:
                sums = (nothing, nothing, np.bincount(where, value, len(texts)))
            out.append((block, texts.tobytes(), np.concatenate(sums).tobytes()))
        return pa.Table.from_pylist([dict(zip(packed.names, row, strict=True)) for row in out], packed)

    packed = pa.schema([("block", pa.int64()), ("ids", pa.binary()), ("sums", pa.binary())])

    def gather(table: pa.Table) -> pa.Table:
        ids = _column(table, "ids", np.uint32)
        sums = np.concatenate([np.frombuffer(x, np.float64).reshape(3, -1) for x in table["sums"].to_pylist()], 1)
        texts, where = np.unique(ids, return_inverse=True)
        base, hits, tree = (np.bincount(where, x, len(texts)).astype(float) for x in sums)
        return pa.table(
            {
                "block": pa.array(np.full(len(texts), table["block"][0].as_py())),
                "idx": pa.array(texts.astype(np.int32)),
                "cold_sum": base,
                "cold_known": hits.astype(np.int64),
                "cold_score": tree,
            }
        )

    cold_values = (
        counts.filter((F.col("kind") == 1) & (F.col("n") <= rare))
        .select(F.pmod("key", F.lit(parts)).cast("int").alias("part"), "key", F.col("n").cast("double").alias("v"))
        .unionAll(logs.select((F.col("part") + parts).cast("int"), "key", "v"))
    )
    sums = (
        passed.filter("part IS NOT NULL")
        .select("part", "block", "ids", "keys")
        .groupBy("part")
        .cogroup(cold_values.groupBy("part"))
        .applyInArrow(resolve, "block bigint, ids binary, sums binary")
        .groupBy("block")
        .applyInArrow(gather, "block bigint, idx int, cold_sum double, cold_known bigint, cold_score double")
    )
    return (
        passed.filter("part IS NULL")
        .join(sums, ["block", "idx"], "left")
        .withColumn("score", F.col("score") + F.coalesce("cold_score", F.lit(0.0)))
        .select(
            "doc_id",
            "held_out",
            "n_tokens",
            (F.col("hot_known") + F.coalesce("cold_known", F.lit(0))).alias("n_known"),
            F.lit(n_all).cast("bigint").alias("train_tokens"),
            (F.col("hot_sum") + F.coalesce("cold_sum", F.lit(0.0))).alias("base_score"),
            "score",
            (-F.col("score") / F.log10(F.lit(2.0)) / F.greatest(F.col("bytes"), F.lit(1))).alias("bits_per_byte"),
        )
    )


def query(spark, sf_dir: str) -> DataFrame:
    from bucketseed.tables import load

    return context_tree_scores(load(spark, sf_dir, "documents"), crc_fold("doc_id", 10) == 0)
