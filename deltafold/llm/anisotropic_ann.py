"""Nearest neighbours by inner product with score-aware (anisotropic) quantisation.

A vector is its coarse centre plus a residual; the residual's direction is coded with four bits for each
subspace and its length kept.  Codes and codebooks minimise a loss in which the error along the vector counts
``eta`` times as much as the error across it, as errors along it change large inner products most.

Every row is coded once and lies in the cell of its centre; large cells are several blocks.  A query visits the
cells whose centres, with the cells' spread, promise the largest products; how many that are is calibrated on the
sample so that its nearest neighbours are found (``AIM``), at every size of the table, and it visits more where these
hold fewer than k candidates.  Its products with all codewords form tables; two
four-bit codes make one byte, so a scan adds one table entry for each pair of subspaces.  Each block proposes its
``rerank`` best by table for each of its queries, scores these exactly in double precision and answers with its ``k``
best; answers are merged by a tree.

Blocks and queries meet as packed rows of stated size, by cell: nothing is collected or broadcast, and the index is
fitted on ``SAMPLE`` vectors at most but holds every row.

Cases: vectors that are null, zero, of another length than most, or hold a null or non-finite component take no
part; fewer candidates than k give them all; equal scores go to the smaller id; rows that repeat a query's id
are not its candidates; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltafold.session import cut

NEIGHBOURS = 20
EVERY = 20
SAMPLE = 6000
#: Cells: about one for each so many rows, between bounds that the sample can support.
ROWS_IN_CELL, CENTRES_LEAST, CENTRES_MOST = 1000, 16, 256
#: Share of the sample's nearest neighbours that the visited cells must hold.
AIM = 0.97
PROBE_QUERIES = 400
CODEWORDS = 16
WIDTH = 4  # dimensions of a subspace
RERANK = 800
ROWS_IN_BLOCK = 8192
QUERIES_IN_BLOCK = 1024
FAN_IN = 16
THRESHOLD = 0.2  # of a unit vector's inner product, above which errors matter


def _nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return ((centres**2).sum(1)[None, :] - 2 * x @ centres.T).argmin(1)


def _kmeans(x: np.ndarray, k: int, rounds: int, rng) -> np.ndarray:
    centres = x[rng.permutation(len(x))[:k]].copy()
    for _ in range(rounds):
        which = _nearest(x, centres)
        for c in np.unique(which):
            centres[c] = x[which == c].mean(0)
    return centres


class Quantiser:
    """Coarse centres and one codebook for each subspace of the residuals' directions."""

    def __init__(self, centres: np.ndarray, books: np.ndarray, eta: float):
        self.centres, self.books, self.eta = centres, books, eta  # books: subspaces x codewords x width
        self.spread, self.visits = np.zeros(len(centres)), len(centres)
        self.rows, self.least = np.zeros(len(centres), np.int64), 0  # rows of each cell; rows that a query must meet

    def _residual(self, x: np.ndarray):
        which = _nearest(x, self.centres)
        r = x - self.centres[which]
        size = np.linalg.norm(r, axis=1)
        unit = np.divide(r, size[:, None], out=np.zeros_like(r), where=size[:, None] > 0)
        length = np.linalg.norm(x, axis=1, keepdims=True)
        return which, size, self._split(unit), self._split(np.divide(x, length, out=np.zeros_like(x), where=length > 0))

    def _split(self, x: np.ndarray) -> np.ndarray:
        parts = self.books.shape[0]
        wide = np.zeros((len(x), parts * WIDTH), x.dtype)
        wide[:, : x.shape[1]] = x
        return wide.reshape(len(x), parts, WIDTH)

    def _codes(self, unit: np.ndarray, along: np.ndarray, sweeps: int = 2) -> np.ndarray:
        """Coordinate descent over subspaces on |e|^2 + (eta - 1) <e, direction>^2."""
        n, parts, _ = unit.shape
        codes = np.zeros((n, parts), np.uint8)
        off = np.zeros((n, parts))
        for m in range(parts):
            codes[:, m] = _nearest(unit[:, m], self.books[m])
            off[:, m] = ((unit[:, m] - self.books[m][codes[:, m]]) * along[:, m]).sum(1)
        total = off.sum(1)
        for _ in range(sweeps):
            for m in range(parts):
                error = ((unit[:, m, None, :] - self.books[m][None]) ** 2).sum(2)
                step = (unit[:, m] * along[:, m]).sum(1)[:, None] - along[:, m] @ self.books[m].T
                rest = total - off[:, m]
                codes[:, m] = (error + (self.eta - 1) * (rest[:, None] + step) ** 2).argmin(1)
                off[:, m] = step[np.arange(n), codes[:, m]]
                total = rest + off[:, m]
        return codes

    def encode(self, x: np.ndarray):
        """(centre, residual's length, bytes of two codes each) for each vector."""
        which, size, unit, along = self._residual(x)
        codes = self._codes(unit, along)
        if codes.shape[1] % 2:
            codes = np.c_[codes, np.zeros(len(codes), np.uint8)]
        return which.astype(np.uint16), size.astype(np.float32), codes[:, ::2] << 4 | codes[:, 1::2]

    def tables(self, queries: np.ndarray) -> np.ndarray:
        """queries x byte positions x 256."""
        t = np.einsum("qmw,mcw->qmc", self._split(queries), self.books)
        if t.shape[1] % 2:
            t = np.concatenate([t, np.zeros_like(t[:, :1])], axis=1)
        return (t[:, ::2, :, None] + t[:, 1::2, None, :]).reshape(len(queries), -1, CODEWORDS**2).astype(np.float32)

    def promise(self, q: np.ndarray) -> np.ndarray:
        """For each query and cell the product that a good row of the cell can have."""
        return q @ self.centres.T + np.linalg.norm(q, axis=1, keepdims=True) * self.spread

    def visited(self, q: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(query, cell) of the cells that each query visits: the calibrated number, and more where these hold fewer
        than ``least`` rows."""
        order = np.argsort(-self.promise(q), axis=1, kind="stable")
        before = np.cumsum(self.rows[order], axis=1) - self.rows[order]
        query, at = np.nonzero((np.arange(order.shape[1]) < self.visits) | (before < self.least))
        return query, order[query, at]

    def calibrate(self, x: np.ndarray, k: int, aim: float = AIM) -> None:
        """Spread of the cells along a random direction, and the least number of visits that finds the aim's
        share of the sample's own nearest neighbours."""
        cell = _nearest(x, self.centres)
        self.spread = np.zeros(len(self.centres))
        for c in np.unique(cell):
            self.spread[c] = np.sqrt(((x[cell == c] - self.centres[c]) ** 2).sum(1).mean() / x.shape[1])
        step = max(1, len(x) // PROBE_QUERIES)
        q = x[::step]
        products = q @ x.T
        products[np.arange(len(q)), np.arange(len(q)) * step] = -np.inf  # a query is not its own neighbour
        near = np.argsort(-products, axis=1)[:, : min(k, len(x) - 1)]
        place = np.argsort(np.argsort(-self.promise(q), axis=1), axis=1)
        need = np.sort(np.take_along_axis(place, cell[near], axis=1).ravel())
        self.visits = int(need[max(0, int(np.ceil(aim * len(need))) - 1)]) + 1 if len(need) else len(self.centres)

    @classmethod
    def fit(cls, x: np.ndarray, centres: int = 64, rounds: int = 4) -> Quantiser:
        rng = np.random.default_rng(0)
        dim = x.shape[1]
        eta = max(1.0, (dim - 1) * THRESHOLD**2 / (1 - THRESHOLD**2))
        parts = -(-dim // WIDTH)
        self = cls(_kmeans(x, min(centres, len(x)), 10, rng), np.zeros((parts, CODEWORDS, WIDTH)), eta)
        _, _, unit, along = self._residual(x)
        for m in range(parts):
            book = _kmeans(unit[:, m], min(CODEWORDS, len(x)), 10, rng)
            self.books[m, : len(book)] = book
        n = len(x)
        for _ in range(rounds):  # codes for the books, then the books that are best for the codes
            codes = self._codes(unit, along)
            size = parts * CODEWORDS * WIDTH
            use = np.zeros((n, parts, CODEWORDS, WIDTH))
            rows = np.arange(n)
            for m in range(parts):
                use[rows, m, codes[:, m]] = along[:, m]
            use = use.reshape(n, size)
            counts = np.stack([np.bincount(codes[:, m], minlength=CODEWORDS) for m in range(parts)]).astype(float)
            left = (eta - 1) * (use.T @ use) + np.diag(np.repeat(counts.ravel(), WIDTH) + 1e-3)
            goal = (unit * along).sum((1, 2))
            right = (eta - 1) * (use.T @ goal) + 1e-3 * self.books.ravel()
            mean = np.zeros((parts, CODEWORDS, WIDTH))
            for m in range(parts):
                np.add.at(mean[m], codes[:, m], unit[:, m])
            self.books = np.linalg.solve(left, right + mean.ravel()).reshape(self.books.shape)
        return self


def _best(ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    return np.lexsort((ids, -scores))[:k]


def scan(quantiser: Quantiser, cell: int, ids: np.ndarray, size: np.ndarray, codes: np.ndarray, x: np.ndarray, query_ids: np.ndarray, q: np.ndarray, k: int, rerank: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """The k best ids and exact scores of a block for each query."""
    out, base, columns = [], q @ quantiser.centres[cell], np.ascontiguousarray(codes.T)
    for at in range(0, len(q), 64):
        tables = quantiser.tables(q[at : at + 64])
        for i, table in enumerate(tables, at):
            near = np.zeros(len(x), np.float32)
            for row, code in zip(table, columns, strict=True):
                near += row[code]
            near = base[i] + size * near
            near[ids == query_ids[i]] = -np.inf
            some = np.argpartition(-near, rerank)[:rerank] if len(near) > rerank else np.arange(len(near))
            some = some[ids[some] != query_ids[i]]
            exact = (x[some] * q[i]).sum(axis=1)
            top = _best(ids[some], exact, k)
            out.append((ids[some][top], exact[top]))
    return out


_CODED = "cell int, id long, size float, code binary, v array<double>"
_CODED_ARROW = pa.schema([("cell", pa.int32()), ("id", pa.int64()), ("size", pa.float32()), ("code", pa.binary()), ("v", pa.list_(pa.float64()))])
_BLOCK = "cell int, block int, n int, ids binary, sizes binary, codes binary, vectors binary"
_BLOCK_ARROW = pa.schema([("cell", pa.int32()), ("block", pa.int32()), ("n", pa.int32()), ("ids", pa.binary()), ("sizes", pa.binary()), ("codes", pa.binary()), ("vectors", pa.binary())])
_ASKED = "cell int, q_n int, q_ids binary, q_vectors binary"
_ASKED_ARROW = pa.schema([("cell", pa.int32()), ("q_n", pa.int32()), ("q_ids", pa.binary()), ("q_vectors", pa.binary())])
_FOUND = "part int, query long, ids array<long>, scores array<double>"
_FOUND_ARROW = pa.schema([("part", pa.int32()), ("query", pa.int64()), ("ids", pa.list_(pa.int64())), ("scores", pa.list_(pa.float64()))])


def _matrix(column) -> np.ndarray:
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    flat = pa.concat_arrays(flat.chunks) if isinstance(flat, pa.ChunkedArray) else flat
    return flat.flatten().to_numpy(zero_copy_only=False).astype("<f8").reshape(len(flat), -1)


def _code(quantiser: Quantiser):
    """Rows with their cell and code: the only time that a row is coded."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                which, size, codes = quantiser.encode(_matrix(batch["v"]))
                yield pa.record_batch([pa.array(which.astype(np.int32)), batch["id"], pa.array(size), pa.array([c.tobytes() for c in codes], pa.binary()), batch["v"]], schema=_CODED_ARROW)

    return run


def _visits(quantiser: Quantiser):
    """A query once for each cell that it visits."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                query, cells = quantiser.visited(_matrix(batch["v"]))
                out = batch.take(pa.array(query))
                yield pa.record_batch([pa.array(cells.astype(np.int32)), out["id"], out["v"]], names=["cell", "id", "v"])

    return run


def _pack(table: pa.Table) -> pa.Table:
    joined = lambda c: b"".join(table[c].to_pylist())
    row = [table["cell"][0].as_py(), table["block"][0].as_py(), table.num_rows, table["id"].to_numpy().astype("<i8").tobytes(), table["size"].to_numpy().astype("<f4").tobytes(), joined("code"), _matrix(table["v"]).tobytes()]
    return pa.table({f.name: pa.array([x], f.type) for f, x in zip(_BLOCK_ARROW, row, strict=True)}, schema=_BLOCK_ARROW)


def _pack_queries(table: pa.Table) -> pa.Table:
    row = [table["cell"][0].as_py(), table.num_rows, table["id"].to_numpy().astype("<i8").tobytes(), _matrix(table["v"]).tobytes()]
    return pa.table({f.name: pa.array([x], f.type) for f, x in zip(_ASKED_ARROW, row, strict=True)}, schema=_ASKED_ARROW)


def _scan_blocks(quantiser: Quantiser, k: int, rerank: int):
    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                ids, x = np.frombuffer(r["ids"], "<i8"), np.frombuffer(r["vectors"], "<f8").reshape(r["n"], -1)
                q_ids, q = np.frombuffer(r["q_ids"], "<i8"), np.frombuffer(r["q_vectors"], "<f8").reshape(r["q_n"], -1)
                found = scan(quantiser, r["cell"], ids, np.frombuffer(r["sizes"], "<f4"), np.frombuffer(r["codes"], np.uint8).reshape(r["n"], -1), x, q_ids, q, k, rerank)
                part = (r["cell"] * 31 + r["block"]) % FAN_IN
                yield pa.record_batch([pa.array([part] * len(q_ids), pa.int32()), pa.array(q_ids), pa.array([f[0] for f in found], pa.list_(pa.int64())), pa.array([f[1] for f in found], pa.list_(pa.float64()))], schema=_FOUND_ARROW)

    return run


def _merge(k: int):
    """The k best of each query's answers."""

    def run(table: pa.Table) -> pa.Table:
        lists = table["ids"].combine_chunks()
        n = pa.compute.list_value_length(lists).to_numpy(zero_copy_only=False)
        query = np.repeat(table["query"].to_numpy(), n)
        ids = pa.compute.list_flatten(table["ids"]).to_numpy()
        scores = pa.compute.list_flatten(table["scores"]).to_numpy()
        order = np.lexsort((ids, -scores, query))
        query, ids, scores = query[order], ids[order], scores[order]
        head = np.flatnonzero(np.r_[True, query[1:] != query[:-1]]) if len(query) else np.zeros(0, int)
        size = np.diff(np.r_[head, len(query)])
        rank = np.arange(len(query)) - np.repeat(head, size)
        keep = rank < k
        cuts = np.r_[0, np.cumsum(np.minimum(size, k))].astype(np.int32)
        make = lambda x: pa.ListArray.from_arrays(pa.array(cuts), pa.array(x[keep]))
        return pa.table({"part": pa.array([0] * len(head), pa.int32()), "query": pa.array(query[head]), "ids": make(ids), "scores": make(scores)}, schema=_FOUND_ARROW)

    return run


def valid_vectors(table: DataFrame, id_col: str, vector_col: str) -> DataFrame:
    """(id, v) of the rows that take part."""
    v = F.col(vector_col).cast("array<double>")
    rows = table.where(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("id"), v.alias("v"))
    ok = F.forall("v", lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < float("inf"))) & F.exists("v", lambda c: c != 0)
    rows = rows.where(F.coalesce(ok, F.lit(False)))
    common = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), "d").first()
    return rows.where(F.size("v") == (common["d"] if common else 0))


def nearest_neighbours(table: DataFrame, queries, k: int = NEIGHBOURS, id_col: str = "vec_id", vector_col: str = "embedding", rerank: int = RERANK, aim: float = AIM) -> DataFrame:
    """(query_id, rank, vec_id, score) of the k nearest rows found for each row where ``queries`` (a condition
    on a column named id) holds."""
    rows = valid_vectors(table, id_col, vector_col)
    n = rows.count()
    schema = "query_id long, rank int, vec_id long, score double"
    sample = rows.where(F.pmod(F.xxhash64("id"), F.lit(max(1, n // SAMPLE))) == 0).select("v").limit(2 * SAMPLE).collect()
    x = np.array([r["v"] for r in sample] or [r["v"] for r in rows.select("v").limit(SAMPLE).collect()])
    if len(x) == 0:
        return table.sparkSession.createDataFrame([], schema)
    quantiser = Quantiser.fit(x, max(1, min(CENTRES_MOST, max(CENTRES_LEAST, n // ROWS_IN_CELL), len(x) // 4)))
    quantiser.calibrate(x, k, aim)
    coded = cut(rows.mapInArrow(_code(quantiser), _CODED))
    held = coded.groupBy("cell").count()  # a row for each cell
    for cell, count in held.collect():
        quantiser.rows[cell] = count
    own = rows.where(queries).groupBy("id").count().agg(F.max("count")).first()[0]
    quantiser.least = k + (own or 0)  # rows with the query's id are not its candidates
    blocks_of = held.select("cell", F.ceil(F.col("count") / ROWS_IN_BLOCK).cast("int").alias("blocks"))
    dealt = coded.join(F.broadcast(blocks_of), "cell").withColumn("block", F.pmod(F.xxhash64("id", F.hash("v")), F.col("blocks")).cast("int"))
    blocks = dealt.groupBy("cell", "block").applyInArrow(_pack, _BLOCK)
    visits = rows.where(queries).mapInArrow(_visits(quantiser), "cell int, id long, v array<double>")
    asked_of = cut(visits).transform(lambda v: v.join(F.broadcast(v.groupBy("cell").agg(F.ceil(F.count("*") / QUERIES_IN_BLOCK).cast("int").alias("lots"))), "cell"))
    asked = asked_of.withColumn("lot", F.pmod(F.xxhash64("id", F.hash("v"), F.lit(1)), F.col("lots")).cast("int")).groupBy("cell", "lot").applyInArrow(_pack_queries, _ASKED)
    partitions = max(int(table.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    met = blocks.join(asked, "cell").repartition(4 * partitions, "cell", "block", F.md5("q_ids"))
    found = met.mapInArrow(_scan_blocks(quantiser, k, rerank), _FOUND)
    lots = max(1, n // (20 * QUERIES_IN_BLOCK))
    lot = F.pmod(F.xxhash64("query"), F.lit(lots)).cast("int")
    # each query's answers meet in FAN_IN parts first
    found = found.withColumn("lot", lot).groupBy("lot", "part").applyInArrow(lambda t: _merge(k)(t.drop_columns(["lot"])), _FOUND)
    found = found.withColumn("lot", lot).groupBy("lot").applyInArrow(lambda t: _merge(k)(t.drop_columns(["lot"])), _FOUND)
    return cut(found).select(F.col("query").alias("query_id"), F.posexplode(F.arrays_zip("ids", "scores")).alias("at", "f")).select("query_id", (F.col("at") + 1).cast("int").alias("rank"), F.col("f.ids").alias("vec_id"), F.col("f.scores").alias("score"))


def op9_nearest_neighbours(spark, sf_dir: str) -> DataFrame:
    """The nearest-neighbour contract on ``embeddings``."""
    return nearest_neighbours(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), F.pmod("id", F.lit(EVERY)) == 0)
