"""Jaccard join of word-n-gram sets with a token-group matrix.

Every pair of documents whose shingle sets reach the threshold is found:

1. Shingles are counted in packed form (:mod:`.blocks`). A document with a partner
   has at least the threshold's share of its shingles in some other document, so most
   documents leave here. Equal sets become one class.
2. Similar classes are put into groups, twice, by the smallest hash of their shared
   shingles under two permutations; inside a group of bounded size all overlaps come
   from one product of token matrices. Their links give provisional components.
3. Components, cut into groups of bounded size, form the token-group matrix: rows
   (token, group) of each group's token union, of which only the rarest tokens that
   any qualifying pair must share are kept. Two groups of different components that
   share such a token become candidates (a token of many groups is cut by document size and
   dealt further, so its groups meet in many tasks); a document's overlap with the other group's
   union bounds its overlap with every member, and only a group that this bound lets
   through is opened. Links between documents of one component need no second look.

No list of a token's documents is expanded into pairs inside a component, so a large
group of copies or near copies costs a linear number of rows.

Null and empty texts have no shingles and link with nothing; texts shorter than the
shingle have one, their whole word sequence. Repeated rows are linked with each other.
A row without id links like any other, and two documents may be joined through it alone;
a component's name is the least id in it, null only if none of its rows has an id. Other
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.components import connected_components
from ..session import drop_stage, release, stage
from .blocks import REQUEST, bucket_count, count_in_buckets, docs_of, expand, mix, places, request_batches, word_blocks

#: Members of a group at most; bounds a task's matrices.
GROUP = 128
#: Columns of a token matrix multiplied at a time.
SLICE = 8192
#: Groups that one token brings to a task; a token of more is cut.
LIST = 2000

SETS = "doc_id long, n_shingles long, set_hash binary, n_own long, tokens binary"


def shingle_keys(ids: np.ndarray, lengths: np.ndarray, vocab: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """(document, key) of the distinct shingles of each document, ordered by both."""
    h, at = vocab[ids], places(lengths)
    of = np.repeat(np.arange(len(lengths)), lengths)
    start = np.flatnonzero(np.repeat(lengths, lengths) - at >= width)
    key = np.full(len(start), width, np.uint64)
    for k in range(width):
        key = mix(key + h[start + k])
    doc = of[start]
    for d in np.flatnonzero((lengths > 0) & (lengths < width)):
        lo = int(lengths[:d].sum()) if d else 0
        x = np.full(1, lengths[d], np.uint64)
        for w in h[lo : lo + int(lengths[d])]:
            x = mix(x + w)
        doc, key = np.append(doc, d), np.append(key, x)
    by = np.lexsort((key, doc))
    doc, key = doc[by], key[by]
    keep = np.ones(len(key), bool)
    keep[1:] = (doc[1:] != doc[:-1]) | (key[1:] != key[:-1])
    return doc[keep], key[keep]


def _ask(blocks: DataFrame, width: int, buckets: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                _, _, lengths = docs_of(r["docs"])
                _, key = shingle_keys(expand(r["seq"], np.int32), lengths, expand(r["vocab"], np.uint64), width)
                uniq, n = np.unique(key, return_counts=True)
                yield request_batches(r["block"], uniq, [n], buckets)

    return blocks.mapInArrow(run, REQUEST)


def _shared(blocks: DataFrame, replies: DataFrame, width: int, percent: int) -> DataFrame:
    """Each document's set size and, where enough of it occurs elsewhere, its shared shingles, rarest first."""

    def run(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        own = next(r for r in rows if r["docs"] is not None)
        doc_ids, _, lengths = docs_of(own["docs"])
        doc, key = shingle_keys(expand(own["seq"], np.int32), lengths, expand(own["vocab"], np.uint64), width)
        uniq, inv = np.unique(key, return_inverse=True)
        got = [expand(r["counts"], np.uint64) for r in sorted((r for r in rows if r["docs"] is None), key=lambda r: r["bucket"])]
        freq = np.concatenate(got)[inv] if got else np.zeros(0, np.uint64)
        size = np.bincount(doc, minlength=len(lengths))
        twice = np.bincount(doc[freq > 1], minlength=len(lengths))
        stays = (size > 0) & (100 * twice >= percent * size)
        ends = np.cumsum(size)
        hashes, tokens = [], []
        for d in range(len(lengths)):
            if not stays[d]:
                hashes.append(None)
                tokens.append(None)
                continue
            k, f = key[ends[d] - size[d] : ends[d]], freq[ends[d] - size[d] : ends[d]]
            hashes.append(xxhash.xxh3_128_digest(k.tobytes()))
            k, f = k[f > 1], f[f > 1]
            tokens.append(k[np.lexsort((k, f))].tobytes())
        return pa.table({"doc_id": pa.array(doc_ids, pa.int64()), "n_shingles": pa.array(size.astype(np.int64)), "set_hash": pa.array(hashes, pa.binary()), "n_own": pa.array((size - twice).astype(np.int64)), "tokens": pa.array(tokens, pa.binary())})

    none = F.lit(None).cast("binary")
    asked = replies.where("block >= 0").select("block", "bucket", "counts", none.alias("docs"), none.alias("seq"), none.alias("vocab"))
    own = blocks.select("block", F.lit(0).alias("bucket"), none.alias("counts"), "docs", "seq", "vocab")
    return asked.unionByName(own).groupBy("block").applyInArrow(run, SETS)


def _overlaps(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections between two lists of token sets, as one matrix product."""
    key = np.concatenate([*left, *right])
    side = np.repeat(np.arange(len(left) + len(right)), [len(x) for x in (*left, *right)])
    _, col, n = np.unique(key, return_inverse=True, return_counts=True)
    number = np.cumsum(n > 1) - 1
    keep = n[col] > 1
    row, col = side[keep], number[col[keep]]
    out = np.zeros((len(left), len(right)), np.float32)
    width = int((n > 1).sum())
    by = np.argsort(col, kind="stable")
    row, col = row[by], col[by]
    for lo in range(0, width, SLICE):
        a, b = np.searchsorted(col, [lo, lo + SLICE])
        m = np.zeros((len(left) + len(right), min(SLICE, width - lo)), np.float32)
        m[row[a:b], col[a:b] - lo] = 1
        out += m[: len(left)] @ m[len(left) :].T
    return out.astype(np.int64)


def _reach(overlap: np.ndarray, nx: np.ndarray, ny: np.ndarray, percent: int) -> np.ndarray:
    return 100 * overlap >= percent * (nx[:, None] + ny[None, :] - overlap)


def _stars(x: np.ndarray, y: np.ndarray, size: int) -> np.ndarray:
    """The smallest index reachable from each of ``size`` nodes over links (x, y)."""
    root = np.arange(size)
    while True:
        low = np.minimum(root[x], root[y])
        new = root.copy()
        np.minimum.at(new, root[x], low)
        np.minimum.at(new, root[y], low)
        new = new[new]
        if (new == root).all():
            return root
        root = new


EDGES = "src long, dst long"


def _sets(table: pa.Table) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    return table["node"].to_numpy(), table["n_shingles"].to_numpy(), [np.frombuffer(b, np.uint64) for b in table["tokens"].to_pylist()]


def _edges(pairs: list[tuple[np.ndarray, np.ndarray]]) -> pa.Table:
    src = np.concatenate([p[0] for p in pairs]) if pairs else np.zeros(0, np.int64)
    dst = np.concatenate([p[1] for p in pairs]) if pairs else np.zeros(0, np.int64)
    return pa.table({"src": pa.array(src, pa.int64()), "dst": pa.array(dst, pa.int64())})


def _minimum_groups(classes: DataFrame, salt: int, percent: int) -> DataFrame:
    """Links inside groups of classes with the same smallest shared shingle under one permutation."""

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            low = [int(mix(np.frombuffer(b, np.uint64) ^ np.uint64(salt)).min().astype(np.int64)) for b in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(low, pa.int64())], names=["node", "low"])

    lows = stage(classes.select("node", "tokens").mapInArrow(first, "node long, low long"), "join-lows")
    many = lows.groupBy("low").agg(F.count("*").alias("n")).where("n > 1")
    # a group beyond the bound is cut at random; other permutations and step 3 find the links across
    cut = F.pmod(F.xxhash64("node", F.lit(salt)), F.ceil(F.col("n") / F.lit(GROUP)).cast("long"))
    placed = lows.join(many, "low").select("node", "low", cut.alias("cut"))

    def link(table: pa.Table) -> pa.Table:
        node, n, sets = _sets(table)
        out = []
        by = np.argsort(n, kind="stable")
        for lo in range(0, len(by), 4 * GROUP):  # a random cut may exceed the bound a little, equal ids much
            part = by[lo : lo + 4 * GROUP]
            own = [sets[i] for i in part]
            x, y = np.nonzero(np.triu(_reach(_overlaps(own, own), n[part], n[part], percent), 1))
            root = _stars(x, y, len(part))
            away = np.flatnonzero(root != np.arange(len(part)))
            out.append((node[part[away]], node[part[root[away]]]))
        return _edges(out)

    return placed.join(classes, "node").groupBy("low", "cut").applyInArrow(link, EDGES)


MATRIX = "token long, grp long, comp long, low long, high long, index boolean"


def _prefix(n: int, own: int, percent: int, both: bool) -> int:
    """How many of the rarest shared tokens must be looked at: one of them is in every partner.

    ``both``: of a partner that is no smaller, where fewer suffice.
    """
    least = -(-2 * percent * n // (100 + percent)) if both else -(-percent * n // 100)
    return max(0, n - least + 1 - own)


def _token_group_matrix(groups: DataFrame, percent: int) -> DataFrame:
    """(token, group) of each group's union of rarest tokens, with the sizes of the members that have it there."""

    def run(table: pa.Table) -> pa.Table:
        node, n, sets = _sets(table)
        own = table["n_own"].to_numpy()
        key = [s[: _prefix(int(n[i]), int(own[i]), percent, False)] for i, s in enumerate(sets)]
        flag = [np.arange(len(k)) < _prefix(int(n[i]), int(own[i]), percent, True) for i, k in enumerate(key)]
        size = np.repeat(n, [len(k) for k in key])
        key, flag = np.concatenate(key), np.concatenate(flag)
        if not len(key):
            return pa.table({c: pa.array([], t) for c, t in (("token", pa.int64()), ("grp", pa.int64()), ("comp", pa.int64()), ("low", pa.int64()), ("high", pa.int64()), ("index", pa.bool_()))})
        # of index and other postings apart, so that the sizes stay narrow
        code, inv = np.unique(np.stack([key, flag.astype(np.uint64)]), axis=1, return_inverse=True)
        inv = inv.reshape(-1)
        low = np.full(code.shape[1], np.iinfo(np.int64).max)
        high = np.zeros(code.shape[1], np.int64)
        np.minimum.at(low, inv, size)
        np.maximum.at(high, inv, size)
        m = code.shape[1]
        return pa.table({"token": pa.array(code[0].astype(np.int64)), "grp": pa.array(np.full(m, table["grp"][0].as_py(), np.int64)), "comp": pa.array(np.full(m, table["comp"][0].as_py(), np.int64)), "low": pa.array(low), "high": pa.array(high), "index": pa.array(code[1] == 1)})

    return groups.groupBy("grp").applyInArrow(run, MATRIX)


def _candidates(matrix: DataFrame, percent: int) -> DataFrame:
    """Pairs of groups of different components that share a token which a link between them would share."""
    live = matrix.groupBy("token").agg(F.min("comp").alias("a"), F.max("comp").alias("b"), F.max("index").alias("i"), F.count("*").alias("n")).where("a != b and i")
    m = matrix.join(live.select("token", F.ceil(F.col("n") / F.lit(LIST)).cast("long").alias("cuts")), "token")
    # a hot token's cells: partners' sizes differ by the ratio at most, so by one step of its powers; then dealt by group
    step = lambda size: F.log(F.col(size)) / F.lit(float(np.log(100 / percent)))
    cells = lambda low, high: F.explode(F.when(F.col("cuts") > 1, F.sequence(F.floor(low).cast("int"), F.floor(high).cast("int"))).otherwise(F.array(F.lit(-1))))
    x = m.where("index").withColumn("cell", cells(step("low"), step("high") + 1 + 1e-6)).withColumn("deal", F.pmod(F.xxhash64("grp"), F.col("cuts")).cast("int")).alias("x")
    y = m.withColumn("cell", cells(step("low"), step("high"))).withColumn("deal", F.explode(F.sequence(F.lit(0), F.col("cuts").cast("int") - 1))).alias("y")
    # the smaller document is on the index side; its partner is at most 100/percent times as large
    near = (F.col("x.comp") != F.col("y.comp")) & (F.col("y.high") >= F.col("x.low")) & (percent * F.col("y.low") <= 100 * F.col("x.high"))
    same = (F.col("x.token") == F.col("y.token")) & (F.col("x.cell") == F.col("y.cell")) & (F.col("x.deal") == F.col("y.deal"))
    return x.join(y, same & near).select(F.least("x.grp", "y.grp").alias("g"), F.greatest("x.grp", "y.grp").alias("h")).distinct()


def _open(candidates: DataFrame, groups: DataFrame, percent: int, sizes: bool = False) -> DataFrame:
    """Bound each member's overlap with the other group's union; open the groups that qualify. ``sizes`` adds those of PAIRS."""

    def pack(table: pa.Table) -> pa.Table:
        node, n, sets = _sets(table)
        sizes = np.array([len(s) for s in sets], np.int64)
        return pa.table({"grp": pa.array([table["grp"][0].as_py()], pa.int64()), "head": pa.array([np.concatenate([node, n, sizes]).astype(np.int64).tobytes()], pa.binary()), "body": pa.array([np.concatenate(sets).tobytes()], pa.binary())})

    used = candidates.select(F.col("g").alias("grp")).unionByName(candidates.select(F.col("h").alias("grp"))).distinct()
    packed = stage(groups.join(used, "grp", "left_semi").groupBy("grp").applyInArrow(pack, "grp long, head binary, body binary"), "join-groups")
    both = candidates.join(packed.toDF("g", "gh", "gb"), "g").join(packed.toDF("h", "hh", "hb"), "h").select("gh", "gb", "hh", "hb")

    def unpack(head: bytes, body: bytes):
        node, n, sizes = np.frombuffer(head, np.int64).reshape(3, -1)
        return node, n, np.split(np.frombuffer(body, np.uint64), np.cumsum(sizes)[:-1])

    def qualify(nx: np.ndarray, xs: list[np.ndarray], ny: np.ndarray, ys: list[np.ndarray]) -> np.ndarray:
        union = np.unique(np.concatenate(ys))
        bound = np.array([np.isin(x, union, assume_unique=True).sum() for x in xs])
        least = np.maximum(ny.min(), -(-percent * nx // 100))
        return np.flatnonzero((100 + percent) * bound >= percent * (nx + least))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                gx, nx, xs = unpack(r["gh"], r["gb"])
                gy, ny, ys = unpack(r["hh"], r["hb"])
                q = qualify(nx, xs, ny, ys)
                if not len(q):
                    continue
                back = qualify(ny, ys, nx[q], [xs[i] for i in q])
                if not len(back):
                    continue
                overlap = _overlaps([xs[i] for i in q], [ys[i] for i in back])
                a, b = np.nonzero(_reach(overlap, nx[q], ny[back], percent))
                if sizes:
                    yield _pairs(gx[q[a]], gy[back[b]], overlap[a, b], nx[q[a]], ny[back[b]]).combine_chunks().to_batches()[0] if len(a) else pa.RecordBatch.from_pylist([], schema=_pairs(*[[]] * 5).schema)
                    continue
                yield _edges([(gx[q[a]], gy[back[b]])]).combine_chunks().to_batches()[0] if len(a) else pa.RecordBatch.from_pylist([], schema=pa.schema([("src", pa.int64()), ("dst", pa.int64())]))

    return both.mapInArrow(run, PAIRS if sizes else EDGES)


PAIRS = "x long, y long, common long, nx long, ny long"


def _pairs(*columns) -> pa.Table:
    return pa.table({c.split()[0]: pa.array(v, pa.int64()) for c, v in zip(PAIRS.split(", "), columns, strict=True)})


def _inside(groups: DataFrame, percent: int) -> DataFrame:
    """PAIRS of similar classes of one group."""

    def run(table: pa.Table) -> pa.Table:
        node, n, sets = _sets(table)
        overlap = _overlaps(sets, sets)
        x, y = np.nonzero(np.triu(_reach(overlap, n, n, percent), 1))
        return _pairs(node[x], node[y], overlap[x, y], n[x], n[y])

    return groups.groupBy("grp").applyInArrow(run, PAIRS)


def similar_pairs(docs: DataFrame, width: int = 5, percent: int = 75) -> DataFrame:
    """(a, b, common, na, nb), a < b: all pairs of documents whose shingle sets reach the threshold, with the sizes.

    Classes of equal sets are compared in the groups of :func:`similar_components`, but every
    two groups that share a token which a similar pair would share, also those of one
    component; members are put in at the end, so the pairs are written but once. Ids must
    be unique; rows without id are in no pair.
    """
    spark = docs.sparkSession
    blocks = stage(word_blocks(docs.where("doc_id is not null")), "join-blocks")
    sets = stage(_shared(blocks, count_in_buckets(_ask(blocks, width, bucket_count(blocks, "n_grams")), 1), width, percent).where("set_hash is not null"), "join-sets")
    drop_stage(blocks)
    release(spark)
    # the class is named by its least member
    classes = stage(sets.groupBy("set_hash").agg(F.min("doc_id").alias("node"), F.first("n_shingles").alias("n_shingles"), F.first("n_own").alias("n_own"), F.first("tokens").alias("tokens")), "join-classes")
    members = stage(sets.select("doc_id", "set_hash", "n_shingles").join(classes.select("set_hash", "node"), "set_hash").select("doc_id", "node", "n_shingles"), "join-members")
    drop_stage(sets)
    own = classes.select("node", "n_shingles", "tokens")
    comps = connected_components(stage(_minimum_groups(own, 0x5D1, percent).unionByName(_minimum_groups(own, 0xA37, percent)), "join-links"))
    comps = stage(comps, "join-components")
    cuts = comps.groupBy("component").agg(F.ceil(F.count("*") / F.lit(GROUP)).cast("long").alias("cuts"))
    named = classes.join(comps.join(cuts, "component"), "node", "left")
    cut = F.pmod(F.xxhash64("node"), F.coalesce("cuts", F.lit(1)))
    grp = F.xxhash64(F.coalesce("component", "node"), cut)
    groups = stage(named.select(grp.alias("grp"), grp.alias("comp"), "node", "n_shingles", "n_own", "tokens"), "join-grouped")
    drop_stage(classes)
    release(spark)
    candidates = stage(_candidates(_token_group_matrix(groups, percent), percent), "join-candidates")
    found = stage(_inside(groups, percent).unionByName(_open(candidates, groups, percent, True)), "join-pairs")
    drop_stage(groups)
    release(spark)
    a, b = members.toDF("p", "x", "n"), members.toDF("q", "y", "m")
    across = found.join(a.drop("n"), "x").join(b.drop("m"), "y").select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"), "common", F.when(F.col("p") < F.col("q"), F.col("nx")).otherwise(F.col("ny")).alias("na"), F.when(F.col("p") < F.col("q"), F.col("ny")).otherwise(F.col("nx")).alias("nb"))
    alike = a.join(b, F.col("x") == F.col("y")).where("p < q").select(F.col("p").alias("a"), F.col("q").alias("b"), F.col("n").alias("common"), F.col("n").alias("na"), F.col("n").alias("nb"))
    return across.unionByName(alike)


def similar_components(docs: DataFrame, width: int = 5, percent: int = 75) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row of (doc_id, text).

    Two documents link when 100 * intersection >= percent * union of their shingle sets;
    component_id is the smallest doc_id that links lead to.
    """
    spark = docs.sparkSession
    blocks = stage(word_blocks(docs), "join-blocks")
    sets = stage(_shared(blocks, count_in_buckets(_ask(blocks, width, bucket_count(blocks, "n_grams")), 1), width, percent), "join-sets")
    drop_stage(blocks)
    release(spark)
    # a class may have no id, so classes are numbered; the stage fixes the numbers
    classes = sets.where("set_hash is not null").groupBy("set_hash").agg(F.min("doc_id").alias("least"), F.first("n_shingles").alias("n_shingles"), F.first("n_own").alias("n_own"), F.first("tokens").alias("tokens"))
    classes = stage(classes.withColumn("node", F.monotonically_increasing_id()), "join-classes")
    members = classes.select("node", "n_shingles", "tokens")
    links = stage(_minimum_groups(members, 0x5D1, percent).unionByName(_minimum_groups(members, 0xA37, percent)), "join-links")
    comps = stage(connected_components(links), "join-components")
    release(spark)
    named = classes.join(comps, "node", "left").withColumn("comp", F.coalesce("component", "node"))
    cuts = comps.groupBy("component").agg(F.ceil(F.count("*") / F.lit(GROUP)).cast("long").alias("cuts"))
    sized = named.join(cuts.withColumnRenamed("component", "comp"), "comp", "left")
    cut = F.pmod(F.xxhash64("node"), F.coalesce("cuts", F.lit(1)))
    groups = stage(sized.select(F.xxhash64("comp", cut).alias("grp"), "comp", "node", "n_shingles", "n_own", "tokens"), "join-grouped")
    candidates = stage(_candidates(_token_group_matrix(groups, percent), percent), "join-candidates")
    more = _open(candidates, groups, percent)
    final = stage(connected_components(stage(comps.select(F.col("node").alias("src"), F.col("component").alias("dst")).unionByName(more), "join-links")), "join-components")
    of = classes.select("set_hash", "least", "node").join(final, "node", "left")
    names = of.where("component is not null").groupBy("component").agg(F.min("least").alias("name"))
    by_set = of.join(names, "component", "left").select("set_hash", F.when(F.col("component").isNull(), F.col("least")).otherwise(F.col("name")).alias("component_id"))
    apart = F.col("set_hash").isNull()
    linked = sets.where(~apart).select("doc_id", "n_shingles", "set_hash").join(by_set, "set_hash", "left").select("doc_id", "n_shingles", "component_id")
    return linked.unionByName(sets.where(apart).select("doc_id", "n_shingles", F.col("doc_id").alias("component_id")))
