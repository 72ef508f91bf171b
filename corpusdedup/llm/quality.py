"""Quality rules judged by an isolation forest.

Rule statistics of a text become a vector of rates; the forest's random splits
isolate unusual vectors after few steps. All labelled rows (of rows that repeat an id,
one) make the model: the rows of good quality populate the trees, and the splits fall
anywhere in the box that all labelled rows span, so a region that only bad rows enter
is cut off early. As the method has it, a tree holds ``PER_TREE`` rows; each tree draws
its own from all good rows. The threshold on the anomaly score is the one that costs
least over all labelled rows, a rejected good row counting ``GOOD_WEIGHT`` times a kept
bad one. Only counts, the box and the trees' rows come to the driver.

Texts are measured whole. Null and empty texts have no words and fail the base rule,
as do texts of fewer than 10 words or with over a fifth of their words in repeated
windows; only others are judged by the forest. Without labelled rows the trees draw
from all rows and the threshold is a fixed 0.65; with labels
of one kind only, nothing is rejected beyond the base rule. Ties at the threshold
are kept. Rows may repeat; extra columns are carried by :func:`keep_good` untouched.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import drop_stage, shuffle_partitions, stage
from .blocks import mix, words_of

TREES, PER_TREE, WINDOW = 100, 256, 5
GOOD_WEIGHT = 40.0
SYMBOLS, LOUD = b"#*$%&|<>", b"!?"
UPPER = bytes(range(65, 91))
SPACES = b" \t\n\x0b\x0c\r"

STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
RATES = ("symbols", "upper", "loud", "word_length", "dup_lines", "repeats", "distinct", "length")


def _without(text: bytes, chars: bytes) -> int:
    return len(text.translate(None, chars))


def repeat_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words inside windows of ``window`` words that the text has twice or more, first ones included."""
    n = len(words)
    if n <= window:
        return 0
    number: dict[bytes, int] = {}
    for w in words:
        if w not in number:
            number[w] = len(number)
    if len(number) == n:
        return 0
    ids = np.fromiter(map(number.__getitem__, words), np.int64, n)
    code = ids[: n - window + 1]
    for k in range(1, window):  # exact: pairs are renumbered at each step
        _, code = np.unique(code * len(number) + ids[k : n - window + 1 + k], return_inverse=True)
    often = np.bincount(code)[code] > 1
    if not often.any():
        return 0
    edge = np.zeros(n + 1, np.int64)
    at = np.flatnonzero(often)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + window, -1)
    return int((np.cumsum(edge[:-1]) > 0).sum())


def measure(text: bytes | None) -> tuple[tuple[int, ...], tuple[float, ...]]:
    """The rule statistics and the rates that the forest sees."""
    text = text or b""
    words = words_of(text)
    n = len(words)
    dense = text.translate(None, SPACES)
    chars = len(dense) if dense.isascii() else len(dense.decode("utf-8", "replace"))
    symbols = len(text) - _without(text, SYMBOLS)
    seen: set[bytes] = set()
    dup = lines = 0
    for line in text.split(b"\n"):
        if line.strip(SPACES):
            lines += 1
            if line in seen:
                dup += 1
            else:
                seen.add(line)
    repeats = repeat_words(words)
    per = max(chars, 1)
    rates = (symbols / per, (len(text) - _without(text, UPPER)) / per, (len(text) - _without(text, LOUD)) / per, min(chars / max(n, 1), 50.0) / 50, dup / max(lines, 1), repeats / max(n, 1), len(set(words)) / max(n, 1) ** 0.9, min(np.log1p(n), 12.0) / 12)
    return (n, chars, symbols, dup, repeats), rates


def failed_base(n_words: int, n_repeat_words: int) -> bool:
    return n_words < 10 or 100 * n_repeat_words > 20 * n_words


@dataclass(frozen=True)
class Forest:
    """Trees as arrays of nodes: split feature (-1: leaf), split value, children, path length at a leaf."""

    feature: np.ndarray
    value: np.ndarray
    left: np.ndarray
    right: np.ndarray
    path: np.ndarray
    roots: np.ndarray
    norm: float

    def scores(self, x: np.ndarray) -> np.ndarray:
        """2 ** -(mean path length / expected length): near 1 for anomalies."""
        total = np.zeros(len(x))
        for root in self.roots:
            at = np.full(len(x), root)
            live = np.flatnonzero(self.feature[at] >= 0)
            while len(live):
                node = at[live]
                go = x[live, self.feature[node]] < self.value[node]
                at[live] = np.where(go, self.left[node], self.right[node])
                live = live[self.feature[at[live]] >= 0]
            total += self.path[at]
        return np.exp2(-total / len(self.roots) / self.norm)


def expected_path(n: int) -> float:
    """Mean depth of an unsuccessful search in a random binary tree of n leaves."""
    return 0.0 if n < 2 else 1.0 if n == 2 else 2 * (np.log(n - 1) + 0.5772156649015329) - 2 * (n - 1) / n


def grow(rows: np.ndarray, box: np.ndarray, trees: int = TREES, per_tree: int = PER_TREE, seed: int = 7) -> Forest:
    """Isolation trees that each draw from ``rows``."""
    rng = np.random.default_rng(seed)
    return _plant((rows[rng.choice(len(rows), min(per_tree, len(rows)), replace=False)] for _ in range(trees)), box, per_tree, min(per_tree, len(rows)), rng)


def _plant(drawn: Iterable[np.ndarray], box: np.ndarray, per_tree: int, size: int, rng: np.random.Generator) -> Forest:
    """A tree over each of ``drawn``, ``size`` rows; splits are uniform in the node's part of ``box`` (low, high by feature)."""
    nodes: list[list] = []
    limit = 2 * int(np.ceil(np.log2(max(per_tree, 2))))

    def build(x: np.ndarray, low: np.ndarray, high: np.ndarray, depth: int) -> int:
        at = len(nodes)
        open_ = np.flatnonzero(high > low)
        if len(x) <= 1 or depth >= limit or not len(open_):
            nodes.append([-1, 0.0, -1, -1, depth + expected_path(len(x))])
            return at
        f = int(rng.choice(open_))
        v = float(rng.uniform(low[f], high[f]))
        nodes.append([f, v, -1, -1, 0.0])
        side = x[:, f] < v
        up, down = high.copy(), low.copy()
        up[f] = down[f] = v
        nodes[at][2] = build(x[side], low, up, depth + 1)
        nodes[at][3] = build(x[~side], down, high, depth + 1)
        return at

    roots = [build(rows, box[0], box[1], 0) for rows in drawn]
    cols = list(zip(*nodes, strict=True))
    return Forest(np.array(cols[0], np.int32), np.array(cols[1]), np.array(cols[2], np.int32), np.array(cols[3], np.int32), np.array(cols[4]), np.array(roots), max(expected_path(size), 1e-9))


@dataclass(frozen=True)
class QualityModel:
    forest: Forest | None
    threshold: float

    def anomaly(self, rates: np.ndarray) -> np.ndarray:
        return self.forest.scores(rates) if self.forest is not None and len(rates) else np.zeros(len(rates))


def calibrate(scores: np.ndarray, bad: np.ndarray, weight: float = GOOD_WEIGHT) -> float:
    """The score above which rejecting costs least: weight x share of good rejected + share of bad kept."""
    if not len(scores) or bad.all() or not bad.any():
        return 1.0
    by = np.argsort(-scores, kind="stable")
    s, b = scores[by], bad[by]
    cost = weight * np.concatenate([[0], np.cumsum(~b)]) / (~b).sum() - np.concatenate([[0], np.cumsum(b)]) / b.sum()
    cost[1:-1][s[1:] == s[:-1]] = np.inf  # no cut between ties
    k = int(np.argmin(cost))
    return float(s[0]) if k == 0 else float(s[-1] - 1e-9) if k == len(s) else float((s[k - 1] + s[k]) / 2)


def fit(docs: DataFrame, labels: DataFrame) -> QualityModel:
    """Grow and calibrate on all labelled rows (documents: doc_id, text; labels: doc_id, quality)."""
    rows = stage(measured(docs), "quality-measured")
    model = fit_measured(rows, labels)
    drop_stage(rows)
    return model


def fit_measured(rows: DataFrame, labels: DataFrame) -> QualityModel:
    """The same from rows of :func:`measured`, which are read more than once."""
    known = labels.where("doc_id is not null and quality is not null").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    one = _one_of_each(rows)
    used = [stage(one.join(known, "doc_id"), "quality-labelled")]
    counts, box = _span(used[0])
    labelled = sum(counts) > 0
    if not labelled:
        used.append(stage(one.withColumn("quality", F.lit(1)), "quality-all"))
        counts, box = _span(used[1])
    n_good, n_bad = counts
    if not n_good + n_bad:
        model = QualityModel(None, 1.0)
    else:
        wide = used[-1]
        rng = np.random.default_rng(7)
        drawn = _draw(wide.where("quality != 0") if n_good else wide, n_good or n_bad)
        forest = _plant(drawn, box, PER_TREE, min(PER_TREE, n_good or n_bad), rng)
        model = QualityModel(forest, _calibrate_all(wide, forest) if labelled else 0.65)
    for table in used:
        drop_stage(table)
    return model


def _one_of_each(rows: DataFrame) -> DataFrame:
    """(doc_id, rates, base_failed) of one row of each id: that with the least rates."""
    one = rows.where("doc_id is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.min(F.struct("rates", "base_failed")).alias("r"))
    return one.select("doc_id", "r.*")


def _rates(docs: DataFrame) -> list:
    """(doc_id, rates, base_failed) of each id, collected: for small tables."""
    return _one_of_each(measured(docs)).collect()


def _span(rows: DataFrame) -> tuple[tuple[int, int], np.ndarray]:
    """How many rows are good and bad, and the box that all of them span."""
    at = [F.col("rates")[k] for k in range(len(RATES))]
    r = rows.agg(F.count_if(F.col("quality") != 0), F.count_if(F.col("quality") == 0), *map(F.min, at), *map(F.max, at)).first()
    return (r[0], r[1]), np.array(r[2:], np.float64).reshape(2, -1)


def _places(ids: np.ndarray, tree: int) -> np.ndarray:
    """Each row's place in the tree's own random order of all rows."""
    return mix(mix(ids.astype(np.int64).view(np.uint64)) + np.uint64((tree + 1) * 0x9E3779B97F4A7C15 % 2**64))


def _draw(rows: DataFrame, n: int, trees: int = TREES, per_tree: int = PER_TREE) -> list[np.ndarray]:
    """For each tree the rates of ``per_tree`` of the ``n`` rows: those with the first places in its order.

    Only rows below a place that about twice as many pass come to the driver, and
    more where that was too few.
    """
    share = 2 * per_tree / n
    while True:
        below = np.uint64(min(int(share * 2**64), 2**64 - 1))

        def run(batches: Iterator[pa.RecordBatch], below: np.uint64 = below) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                ids = batch.column(0).to_numpy()
                for tree in range(trees):
                    place = _places(ids, tree)
                    at = np.flatnonzero(place <= below)
                    if len(at):
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), tree, np.int32)), pa.array(place[at].view(np.int64)), batch.column(1).take(pa.array(at))], names=["tree", "place", "rates"])

        got = rows.select("doc_id", "rates").mapInArrow(run, "tree int, place long, rates array<double>").toArrow()
        tree, place = got["tree"].to_numpy(), got["place"].to_numpy().view(np.uint64)
        x = np.array(got["rates"].combine_chunks().flatten()).reshape(-1, len(RATES))
        if np.bincount(tree, minlength=trees).min() >= min(per_tree, n):
            by = np.lexsort((place, tree))
            first = np.searchsorted(tree[by], np.arange(trees))
            return [x[by[k : k + min(per_tree, n)]] for k in first]
        share *= 2


def _calibrate_all(rows: DataFrame, forest: Forest) -> float:
    """:func:`calibrate` over all rows that pass the base rules: ranges of scores are added up in tasks of their own."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = forest.scores(_matrix(batch.column(0)))
            yield pa.RecordBatch.from_arrays([pa.array(score), batch.column(1)], names=["score", "bad"])

    judged = rows.where("not base_failed").select("rates", (F.col("quality") == 0).alias("bad")).mapInArrow(run, "score double, bad boolean")
    scores = stage(judged.groupBy("score").agg(F.count_if(~F.col("bad")).alias("good"), F.count_if("bad").alias("bad")), "quality-scores")
    parts = stage(scores.repartitionByRange(shuffle_partitions(rows.sparkSession), F.desc("score")).withColumn("part", F.spark_partition_id()), "quality-ranges")
    told = sorted(parts.groupBy("part").agg(F.sum("good"), F.sum("bad"), F.max("score")).collect(), key=lambda r: -r[3])
    n_good, n_bad = sum(r[1] for r in told), sum(r[2] for r in told)
    if n_good and n_bad:
        before, after, g, b = {}, {}, 0, 0
        for k, r in enumerate(told):
            before[r[0]], after[r[0]] = (g, b), told[k + 1][3] if k + 1 < len(told) else None
            g, b = g + r[1], b + r[2]

        def least(table: pa.Table) -> pa.Table:
            table = table.sort_by([("score", "descending")])
            s, (g0, b0) = table["score"].to_numpy(), before[table["part"][0].as_py()]
            cost = GOOD_WEIGHT * (g0 + np.cumsum(table["good"].to_numpy())) / n_good - (b0 + np.cumsum(table["bad"].to_numpy())) / n_bad
            k = int(np.argmin(cost))
            below = s[k + 1] if k + 1 < len(s) else after[table["part"][0].as_py()]
            return pa.table({"cost": [float(cost[k])], "score": [float(s[k])], "below": pa.array([below], pa.float64())})

        cuts = parts.groupBy("part").applyInArrow(least, "cost double, score double, below double").collect()
        best = min(cuts, key=lambda r: (r.cost, -r.score))
        if best.cost >= 0:  # to reject nothing costs nothing
            threshold = told[0][3]
        else:
            threshold = best.score - 1e-9 if best.below is None else (best.score + best.below) / 2
    else:
        threshold = 1.0
    drop_stage(scores)
    drop_stage(parts)
    return threshold


def _matrix(rates: pa.Array) -> np.ndarray:
    """Rates, a list for each row, as rows of a matrix."""
    return rates.flatten().to_numpy(zero_copy_only=False).reshape(-1, len(RATES))


def measured(docs: DataFrame, carry: list[str] | None = None) -> DataFrame:
    """Statistics, base verdict and rates of every row, after the columns in ``carry`` (doc_id alone by default)."""
    fields = _carried(docs, carry)
    schema = T.StructType([*fields, *T._parse_datatype_string(MEASURED).fields])
    names = [f.name for f in schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [measure(t.as_buffer().to_pybytes() if t.is_valid else None) for t in batch.column(0)]
            stats = np.array([o[0] for o in out], np.int64).reshape(-1, len(STATS))
            failed = np.array([failed_base(s[0], s[4]) for s in stats.tolist()], bool)
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], *(pa.array(c) for c in stats.T), pa.array(failed), pa.array([o[1] for o in out], pa.list_(pa.float64()))], names=names)

    return docs.select(F.col("text").cast("binary").alias("text"), *(F.col(f"`{f.name}`") for f in fields)).mapInArrow(run, schema)


def _carried(docs: DataFrame, carry: list[str] | None) -> list[T.StructField]:
    return [f for f in docs.schema.fields if f.name in (["doc_id"] if carry is None else carry)]


MEASURED = ", ".join(f"{s} long" for s in STATS) + ", base_failed boolean, rates array<double>"
VERDICT = ", ".join(f"{s} long" for s in STATS) + ", base_failed boolean, anomaly double, kept boolean"


def judge(docs: DataFrame, model: QualityModel, carry: list[str] | None = None) -> DataFrame:
    """Statistics and verdict of every row, after the columns in ``carry`` (doc_id alone by default)."""
    return judge_measured(measured(docs, carry), model)


def judge_measured(rows: DataFrame, model: QualityModel) -> DataFrame:
    """The same from rows of :func:`measured`."""
    fields = rows.schema.fields[: -len(STATS) - 2]
    schema = T.StructType([*fields, *T._parse_datatype_string(VERDICT).fields])
    names = [f.name for f in schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            *rest, failed, rates = batch.columns
            score = model.anomaly(_matrix(rates))
            yield pa.RecordBatch.from_arrays([*rest, failed, pa.array(score), pa.array(~failed.to_numpy(zero_copy_only=False) & (score <= model.threshold))], names=names)

    return rows.mapInArrow(run, schema)


def keep_good(docs: DataFrame, model: QualityModel) -> DataFrame:
    """The rows of ``docs`` that the rules and the forest keep, with all their columns.

    The texts pass the rules and are dropped or passed on in the same task: no shuffle.
    """
    schema = docs.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = schema.fieldNames().index("text")
        for batch in batches:
            out = [measure(t.as_buffer().to_pybytes() if t.is_valid else None) for t in batch.column(at)]
            failed = np.array([failed_base(o[0][0], o[0][4]) for o in out], bool)
            score = model.anomaly(np.array([o[1] for o in out]).reshape(-1, len(RATES)))
            yield batch.filter(pa.array(~failed & (score <= model.threshold)))

    return docs.mapInArrow(run, schema)
