"""Near-duplicate vectors by product quantisation.

Equal vectors of one label are one node from the start. Nodes belong to the list of their nearest coarse centroid, coded by the
residual: each slice of it is replaced by the nearest word of that slice's codebook, and the length of what the code misses is
kept. A neighbour within the threshold's distance lies in a list whose border is no farther than that distance, so a node asks all
such lists, and no link is lost. Lists of one label that lie near each other share blocks of bounded size, a crowded list has several;
a node is sent once to each block, its own or a later one, with a list that it asks: a link's ends ask for each other, so one of them finds it. In a block,
distances to codes come from lookup tables of the asking vector; a pair stays if that distance, less what the code misses,
could still be within the threshold, so the codes lose nothing either. What stays is decided by the cosine of the vectors in double
precision.

Centroids and codebooks are fitted on a bounded sample (``SAMPLE`` nodes, the first in the order of a hash); all nodes are
indexed. The nodes that ask a block are cut into parts of bounded size. A block
returns, for each node with links, how many vectors it links to, and for each group it finds a star of links: rows in proportion
to nodes and the blocks they ask, however dense the group. Where borders hold little apart, as in many dimensions, a label's nodes meet all its blocks: the work then
grows with the square of a label's nodes.

Vectors that are null, zero, or hold nulls or non-finite numbers link with nothing, and neither do those without a label; each
is a component of its own. Vectors of different lengths aren't compared. Rows that share an id are one vector set each for
itself in the counts, and share components by id. Columns beside id, vector and label are ignored. Empty tables give no rows."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathtraces.llm.common import parts, spill
from pathtraces.llm.components import components
from pathtraces.plans.storage import small

THRESHOLD, SAMPLE, SLICE, WORDS = 0.93, 16_384, 8, 64
BLOCK, ASKING, CHUNK, SEED = 2048, 8192, 512, 5
#: More than single precision can miss of a squared distance between unit vectors.
ROUNDING = 1e-4


def usable(vector: str) -> Column:
    """Whether a vector can link with any other."""
    whole = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    return F.coalesce(whole & F.exists(vector, lambda x: x != 0), F.lit(False))


def k_means(x: np.ndarray, k: int, rounds: int = 12, seed: int = SEED) -> np.ndarray:
    """Centroids; empty ones are moved to points drawn anew."""
    rng = np.random.default_rng(seed)
    k = min(k, len(x))
    at = x[rng.choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        near = nearest(x, at)
        n = np.bincount(near, minlength=k)
        sums = np.zeros_like(at)
        np.add.at(sums, near, x)
        at = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], x[rng.integers(0, len(x), k)])
    return at


def squares(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.maximum((x**2).sum(axis=1)[:, None] + (y**2).sum(axis=1) - 2 * x @ y.T, 0)


def nearest(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.concatenate([squares(x[a : a + 4096], y).argmin(axis=1) for a in range(0, len(x), 4096)]) if len(x) else np.empty(0, np.int64)


def chained(x: np.ndarray) -> np.ndarray:
    """The rows, each followed by the nearest one that is left."""
    order, left = [0], np.ones(len(x), bool)
    left[0] = False
    while left.any():
        rest = np.flatnonzero(left)
        order.append(rest[squares(x[order[-1:]], x[rest])[0].argmin()])
        left[order[-1]] = False
    return x[order]


def matrix(column) -> np.ndarray:
    """A list column of Arrow, of one length and without nulls."""
    import pyarrow.compute as pc

    return np.asarray(pc.list_flatten(column)).astype(float).reshape(len(column), -1)


class ProductQuantiser:
    def __init__(self, sample: np.ndarray, lists: int, slice_size: int = SLICE, words: int = WORDS):
        unit = sample / np.linalg.norm(sample, axis=1, keepdims=True)
        self.coarse = chained(k_means(unit, lists))
        rest = unit - self.coarse[nearest(unit, self.coarse)]
        self.cuts = [slice(a, min(a + slice_size, unit.shape[1])) for a in range(0, unit.shape[1], slice_size)]
        self.books = [k_means(rest[:, c], words) for c in self.cuts]
        self.between = np.sqrt(squares(self.coarse, self.coarse))

    def code(self, unit: np.ndarray, lists: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Codes, the length of what they miss, and the part of squared distances that only codes and lists decide."""
        rest = unit - self.coarse[lists]
        codes = np.column_stack([nearest(rest[:, c], book) for c, book in zip(self.cuts, self.books, strict=True)])
        kept = np.column_stack([book[codes[:, k]] for k, book in enumerate(self.books)])
        return codes.astype(np.uint8), np.linalg.norm(rest - kept, axis=1), (kept * (kept + 2 * self.coarse[lists])).sum(axis=1)

    def asked(self, unit: np.ndarray, within: float) -> list[np.ndarray]:
        """All lists of which a vector's neighbours within a distance can be members, the own list of each among them."""
        far = squares(unit, self.coarse)
        own = far.argmin(axis=1)
        between = self.between[own]
        border = np.where(between > 1e-8, (far - far[np.arange(len(unit)), own][:, None]) / np.maximum(2 * between, 1e-8), 0)
        return [np.flatnonzero(row <= within + 1e-6) for row in border]

    def distances(self, unit: np.ndarray, lists: np.ndarray, codes: np.ndarray, fixed: np.ndarray) -> np.ndarray:
        """Squared distances of coded members (rows) to vectors (columns), from tables; single precision."""
        kinds, at = np.unique(lists, return_inverse=True)
        out = np.take(squares(self.coarse[kinds], unit).astype(np.float32), at, axis=0)
        out += fixed[:, None].astype(np.float32)
        for k, (c, book) in enumerate(zip(self.cuts, self.books, strict=True)):
            out -= np.take((2 * book @ unit[:, c].T).astype(np.float32), codes[:, k], axis=0)
        return out


def _stars(linked: np.ndarray, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node of its group) for the groups that a matrix of links makes of its row and column nodes."""
    r, c = linked.nonzero()
    rows, cols = left.copy(), right.copy()
    while True:
        new_rows, new_cols = rows.copy(), cols.copy()
        np.minimum.at(new_rows, r, cols[c])
        np.minimum.at(new_cols, c, new_rows[r])
        if (new_rows == rows).all() and (new_cols == cols).all():
            break
        rows, cols = new_rows, new_cols
    nodes, to = np.concatenate([left, right]), np.concatenate([rows, cols])
    return nodes[nodes != to], to[nodes != to]


def vector_links(nodes: DataFrame, threshold: float = THRESHOLD, sample: int = SAMPLE, lists: int | None = None) -> DataFrame:
    """``nodes``: ``node`` (unique), ``label``, ``vec`` (usable, of one length), ``n`` (vectors that it stands for). Returns rows (``node``, ``to``, ``n``): of a
    link within a group's star (``n`` null), or of the number of other vectors a node links to in one block (``to`` null)."""
    spark = nodes.sparkSession
    total = nodes.count()
    drawn = nodes.select("vec", F.xxhash64("node").alias("h"), "node").orderBy("h", "node").limit(sample).toArrow()
    points = matrix(drawn["vec"])
    quantiser = ProductQuantiser(points, lists or int(np.clip(2 ** round(np.log2(max(total, 1)) / 2), 1, 4096)))
    model = spark.sparkContext.broadcast(quantiser)
    within = float(np.sqrt(max(0.0, 2 - 2 * threshold)))

    def place(batches):
        import pyarrow as pa

        pq = model.value
        for batch in batches:
            x = matrix(batch.column(2))
            own = nearest(x / np.linalg.norm(x, axis=1, keepdims=True), pq.coarse)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(own, pa.int32())], [*batch.schema.names, "list"])

    def ask(batches):
        import pyarrow as pa

        pq = model.value
        for batch in batches:
            for piece in parts(batch):
                x = matrix(piece.column(2))
                asks = pq.asked(x / np.linalg.norm(x, axis=1, keepdims=True), within)
                row = pa.array(np.repeat(np.arange(len(x)), [len(a) for a in asks]))
                yield pa.RecordBatch.from_arrays([*(piece.column(k).take(row) for k in (0, 1, 3)), pa.array(np.concatenate(asks), pa.int32())], ["node", "label", "own", "list"])

    kinds = dict(nodes.dtypes)
    placed = nodes.select("node", "label", "vec", "n").mapInArrow(place, f"node long, label {kinds['label']}, vec {kinds['vec']}, n long, list int")
    placed = spill(placed, "placed")
    sizes = placed.groupBy("label", "list").agg(F.count(F.lit(1)).alias("members"))
    sizes = sizes.withColumn("before", F.sum("members").over(Window.partitionBy("label").orderBy("list")) - F.col("members"))
    sizes = small(spill(sizes, "list-sizes"))
    block = lambda position: F.floor(position / BLOCK).cast("int")
    members = placed.join(sizes, ["label", "list"]).withColumn("own", block(F.col("before") + F.pmod(F.xxhash64("node"), F.col("members"))))
    members = spill(members.select("node", "label", "vec", "n", "list", "own"), "members")
    asks = members.select("node", "label", "vec", "own").mapInArrow(ask, f"node long, label {kinds['label']}, own int, list int").join(sizes, ["label", "list"])
    last = block(F.col("before") + F.col("members") - 1)
    asks = asks.where(last >= F.col("own")).withColumn("block", F.explode(F.sequence(F.greatest("own", block(F.col("before"))), last)))
    asks = spill(asks.select("node", "label", "block").distinct(), "asks")
    crowds = small(spill(asks.groupBy("label", "block").agg(F.ceil(F.count(F.lit(1)) / ASKING).cast("int").alias("a")), "block-sizes"))
    # a block's members meet every part of those who ask
    held = members.withColumn("block", F.col("own")).join(crowds, ["label", "block"]).withColumn("part", F.explode(F.sequence(F.lit(0), F.col("a") - 1))).withColumn("member", F.lit(True))
    asking = asks.join(crowds, ["label", "block"]).withColumn("part", F.pmod(F.xxhash64("node"), F.col("a")).cast("int")).withColumn("member", F.lit(False))
    asking = asking.join(members.drop("label"), "node")
    columns = ["label", "block", "part", "node", "vec", "n", "list", "own", "member"]
    cut = held.select(columns).unionByName(asking.select(columns))

    def compare(group):
        import pyarrow as pa

        pq = model.value
        member = group["member"].to_numpy(zero_copy_only=False).astype(bool)
        x = matrix(group["vec"])
        ids, n, of = group["node"].to_numpy(), group["n"].to_numpy(), group["list"].to_numpy()
        size = np.linalg.norm(x, axis=1)
        unit = x / size[:, None]
        m, q = np.flatnonzero(member), np.flatnonzero(~member)
        codes, missed, fixed = pq.code(unit[m], of[m])
        limit = ((within + missed) ** 2 + ROUNDING).astype(np.float32)[:, None]
        # within a block both ends of a link ask; a node of an earlier block asks for both
        earlier = group["own"].to_numpy() < group["block"].to_numpy()
        back = np.zeros(len(m), np.int64)
        found: list[tuple] = []
        for at in range(0, len(q), CHUNK):
            few = q[at : at + CHUNK]
            near = (pq.distances(unit[few], of[m], codes, fixed) <= limit).T
            near &= ids[few][:, None] != ids[m][None, :]
            rows, cols = near.any(axis=1).nonzero()[0], near.any(axis=0).nonzero()[0]
            if not len(rows):
                continue
            a, b = few[rows], m[cols]
            linked = (x[a] @ x[b].T / (size[a][:, None] * size[b][None, :]) >= threshold) & near[np.ix_(rows, cols)]
            counts = linked @ n[b]
            some = counts > 0
            found.append((ids[a][some], None, counts[some]))
            back[cols] += (n[a] * earlier[a]) @ linked
            nodes_, to = _stars(linked, ids[a], ids[b])
            found.append((nodes_, to, None))
        if back.any():
            found.append((ids[m][back > 0], None, back[back > 0]))
        cols = [[], [], []]
        for node, to, k in found:
            cols[0].append(node)
            cols[1].append(pa.array(to, pa.int64()) if to is not None else pa.nulls(len(node), pa.int64()))
            cols[2].append(pa.array(k, pa.int64()) if k is not None else pa.nulls(len(node), pa.int64()))
        if not found:
            return pa.table({c: pa.array([], pa.int64()) for c in ("node", "to", "n")})
        return pa.table({"node": np.concatenate(cols[0]), "to": pa.chunked_array(cols[1]), "n": pa.chunked_array(cols[2])})

    # dealt out by block and part: by label alone, which a join may leave, all blocks of a crowded label would meet in one task
    cut = cut.repartition("label", "block", "part")
    return cut.groupBy("label", "block", "part").applyInArrow(compare, "node long, to long, n long")


def vector_components(table: DataFrame, id: str = "vec_id", vector: str = "embedding", label: str = "label", threshold: float = THRESHOLD, **settings) -> DataFrame:
    """Per row: ``id``, ``n_links``, ``component_id`` (smallest id that links reach), ``kept`` (it is its own component)."""
    rows = table.select(F.col(id).cast("long").alias("id"), F.col(label).alias("label"), F.col(vector).alias("vec"))
    able = usable("vec") & F.col("label").isNotNull() & F.col("id").isNotNull()
    keyed = rows.withColumn("h1", F.when(able, F.xxhash64("label", "vec"))).withColumn("h2", F.when(able, F.xxhash64(F.lit("second"), "vec", "label")))
    nodes = keyed.where("h1 is not null").groupBy("h1", "h2").agg(F.min("id").alias("node"), F.first("label").alias("label"), F.first("vec").alias("vec"), F.count(F.lit(1)).alias("n"))
    # an id with several vectors is several nodes of that name
    nodes = spill(nodes, "vectors")
    lengths = [r[0] for r in nodes.groupBy(F.size("vec").alias("d")).count().orderBy("d").collect()]
    spark = table.sparkSession
    found = spark.createDataFrame([], "node long, to long, n long")
    for d in lengths:
        found = found.unionByName(vector_links(nodes.where(F.size("vec") == d), threshold, **settings))
    found = spill(found, "vector-links")
    counts = found.where("to is null").groupBy("node").agg(F.sum("n").alias("others"))
    stars = components(found.where("to is not null"), "node", "to")
    named = nodes.select("h1", "h2", "node", "n").join(counts, "node", "left").join(stars, "node", "left")
    named = named.select("h1", "h2", (F.coalesce("others", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "node").alias("component_id"))
    out = keyed.select("id", "h1", "h2").join(named, ["h1", "h2"], "left").select("id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("id") == F.col("component_id"), F.lit(True))).withColumnRenamed("id", id)
