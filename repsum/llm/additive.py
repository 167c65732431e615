"""Approximate nearest neighbours by additive quantisation.

A vector is coded as the sum of one codeword from each of several full-dimensional codebooks.
Codebooks start as residual k-means on a bounded sample and are then refitted together by least
squares on the codes that a beam search gives. Every vector is encoded by beam search and its
norm is stored. A query's inner products with all codewords form lookup tables; a code's score
is the sum of its entries, corrected by the stored norm. The best of these are ranked again by
exact products with the original vectors; the worst score among them is a floor.

No row is lost to the codes: with u the direction of a row's decoded vector, the row is its part
along u plus a rest across it, and the rest adds at most its length times the length of the
query across u to the product. Every row whose bound reaches the floor is ranked exactly too, so
the result is that of brute force however coarse the codes are; coarse codes only cost time.

Queries come in blocks of bounded size against all rows of the index. A task takes a few thousand
rows and some queries at a time: lookup tables and bounds in single precision, with what that loses
added, then products in single precision of what the bounds leave open, then exact ones of what
still reaches the floor, which rises with the best found. Each task keeps its own exact best, and
the tasks' lists meet once per query.

Edge cases: vectors that are null, empty, zero, hold null or non-finite components, or whose
length is not the most frequent one take no part; repeated rows are candidates of their own, but
query rows of one id are one query (its vector that sorts first), whose candidates are the rows
of other ids; ties go to the smaller id; fewer candidates than asked for are all returned; an empty table
yields an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from repsum.plans.scratch import materialise

BOOKS = 8
WORDS = 256
BEAM = 4
#: Rows that codebooks are fitted on, by smallest hash of the id; every row is indexed.
TRAIN_ROWS = 8192
#: Rows whose exact products set the floor.
SHORTLIST = 400
#: Share of the codewords' lengths below which a decoded vector has no direction.
LEAST = 1e-6
#: What sums in single precision lose at most over 64 components, as a share of the lengths that go into them.
SINGLE = 2e-5
#: Queries and rows whose scores stay in a processor's cache together, and pairs that are ranked exactly together.
QUERIES_AT_ONCE, SCAN_ROWS, PAIRS_AT_ONCE = 64, 2048, 1 << 14
QUERY_BLOCK = 4096
#: Rows of the index that one task scans.
TASK_ROWS = 1 << 16


def usable(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(vec_id, v array<double>) of the rows that take part."""
    v = F.transform(F.col(vector_col), lambda x: x.cast("double"))
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & F.col("v").isNotNull() & finite & F.exists("v", lambda x: x != 0.0))
    sizes = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").head()
    return rows.where(F.size("v") == (sizes["n"] if sizes else 0))


def _nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return np.argmin((centres**2).sum(1)[None, :] - 2 * (x @ centres.T), axis=1)


def kmeans(x: np.ndarray, k: int, rounds: int, seed: int) -> np.ndarray:
    rng = np.random.default_rng(seed)
    centres = x[rng.permutation(len(x))[:k]].copy() if len(x) >= k else np.vstack([x, np.zeros((k - len(x), x.shape[1]))])
    for _ in range(rounds):
        at = _nearest(x, centres)
        n = np.bincount(at, minlength=k)
        sums = np.zeros_like(centres)
        np.add.at(sums, at, x)
        centres = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], centres)
    return centres


def encode(x: np.ndarray, books: np.ndarray, beam: int = BEAM) -> np.ndarray:
    """Codes (n, books) by beam search over the residuals."""
    m, k, d = books.shape
    out = np.empty((len(x), m), np.uint8 if k <= 256 else np.uint16)
    norms = (books**2).sum(2)
    for begin in range(0, len(x), 1024):
        part = x[begin : begin + 1024]
        n = len(part)
        rest, codes, cost = part[:, None, :], np.empty((n, 1, 0), out.dtype), None
        for i in range(m):
            fall = norms[i][None, None, :] - 2 * (rest.reshape(-1, d) @ books[i].T).reshape(n, -1, k)
            reach = fall if cost is None else fall + cost[:, :, None]
            flat = reach.reshape(n, -1)
            keep = np.argpartition(flat, min(beam, flat.shape[1]) - 1, axis=1)[:, :beam]
            rows = np.arange(n)[:, None]
            cost, parent, word = flat[rows, keep], keep // k, keep % k
            rest = rest[rows, parent] - books[i][word]
            codes = np.concatenate([codes[rows, parent], word[:, :, None].astype(out.dtype)], axis=2)
        out[begin : begin + 1024] = codes[np.arange(n), np.argmin(cost, axis=1)]
    return out


def decode(codes: np.ndarray, books: np.ndarray) -> np.ndarray:
    return sum(books[i][codes[:, i]] for i in range(len(books)))


def train(x: np.ndarray, m: int = BOOKS, k: int = WORDS, rounds: int = 2, seed: int = 11) -> np.ndarray:
    """Codebooks (m, k, d): residual k-means, then joint least squares on beam-search codes."""
    books, rest = [], x.copy()
    for i in range(m):
        books.append(kmeans(rest, k, 6, seed + i))
        rest = rest - books[-1][_nearest(rest, books[-1])]
    books = np.stack(books)
    for _ in range(rounds):
        codes = encode(x, books)
        at = codes.astype(np.int64) + np.arange(m) * k
        gram, right = np.zeros((m * k, m * k)), np.zeros((m * k, x.shape[1]))
        for i in range(m):
            np.add.at(right, at[:, i], x)
            for j in range(m):
                np.add.at(gram, (at[:, i], at[:, j]), 1)
        gram[np.diag_indices_from(gram)] += 0.1
        right += 0.1 * books.reshape(m * k, -1)  # unused words stay where they are
        books = np.linalg.solve(gram, right).reshape(m, k, -1)
    return books


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def build_index(rows: DataFrame, m: int = BOOKS, k: int = WORDS, train_rows: int = TRAIN_ROWS) -> tuple[DataFrame, np.ndarray | None]:
    """(vec_id, v, codes, norm) of every row, written; and the codebooks."""
    rows = materialise(rows, "vectors")
    sample = rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(train_rows).collect()
    if not sample:
        return rows.withColumn("codes", F.lit(None).cast("binary")).withColumn("norm", F.lit(None).cast("double")), None
    books = train(np.array([r["v"] for r in sample]), m, min(k, max(1, len(sample))))
    shared = rows.sparkSession.sparkContext.broadcast(books)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            x = _matrix(batch.column("v"))
            if not len(x):
                continue
            codes = encode(x, own)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([c.tobytes() for c in codes], pa.binary()), pa.array(np.sqrt((x**2).sum(1)))], names=["vec_id", "v", "codes", "norm"])

    n = rows.count()
    tasks = max(rows.sparkSession.sparkContext.defaultParallelism, -(-n // TASK_ROWS))
    dealt = rows.repartition(tasks, F.xxhash64("vec_id"))
    return materialise(dealt.mapInArrow(run, "vec_id long, v array<double>, codes binary, norm double"), "codes"), books


def products(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Inner products summed in the order of the components, as SQL sums them."""
    out = x[:, 0] * q[0]
    for d in range(1, x.shape[1]):
        out += x[:, d] * q[d]
    return out


def search_block(index: DataFrame, books: np.ndarray, query_ids: np.ndarray, queries: np.ndarray, want: int, shortlist: int = SHORTLIST) -> DataFrame:
    """(query_id, vec_id, score): each query's best of all rows of the index, not itself."""
    shared = index.sparkSession.sparkContext.broadcast((books, query_ids, queries))

    queries_at_once, scan_rows, pairs_at_once = QUERIES_AT_ONCE, SCAN_ROWS, PAIRS_AT_ONCE

    def scan(ids: np.ndarray, x: np.ndarray, codes: np.ndarray, norm: np.ndarray) -> Iterator[tuple]:
        own, qids, qs = shared.value
        order = np.argsort(ids, kind="stable")
        ids, x, codes, norm = ids[order], x[order], codes[order], norm[order]
        made = decode(codes, own)
        length = np.sqrt((made**2).sum(1))
        size = np.maximum(length, 1e-300)
        reach = np.sqrt((own**2).sum(2)).max(1).sum()
        clear = length > LEAST * reach
        along = np.where(clear, (x * made).sum(1) / size, 0.0)
        across = np.where(clear, np.sqrt(((x - (along / size)[:, None] * made) ** 2).sum(1)), norm)
        del made
        # in single precision rows are parts of the longest, queries have length 1; ``lost`` bounds what that loses
        longest, lost = norm.max(), SINGLE * max(1.0, x.shape[1] / 64)
        single = lambda a: a[:, None].astype(np.float32)
        turn, loose = single(np.where(clear, reach / size, 0.0)), single(np.where(clear, lost * reach / size, 0.0))
        part, rest, slack = single(along / longest), single(across / longest), single(lost * norm / longest)
        slack += np.abs(part) * loose
        thin = (x / longest).astype(np.float32)
        for begin in range(0, len(qids), queries_at_once):
            q, asked = qs[begin : begin + queries_at_once], qids[begin : begin + queries_at_once]
            far = np.sqrt((q**2).sum(1))
            plain = bool(np.isfinite(longest) and (norm > 0).all() and (far > 0).all() and np.isfinite(far * longest).all())
            if plain:
                unit = (q / far[:, None]).astype(np.float32)
                tables = (np.einsum("mkd,qd->mqk", own, q / far[:, None]) / reach).transpose(0, 2, 1).astype(np.float32, order="C")
            best_of, best_id, best = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
            floor = np.full(len(q), -np.inf)
            for first in range(0, len(ids), scan_rows):
                rows = slice(first, first + scan_rows)
                if plain:
                    near = tables[0].take(codes[rows, 0], axis=0)
                    for i in range(1, len(own)):
                        near += tables[i].take(codes[rows, i], axis=0)
                    near *= turn[rows]
                    if first == 0 and len(near) > shortlist > want:  # the best by their codes set the floor
                        score = near * single(norm[rows] / longest)
                        score[ids[rows, None] == asked] = -np.inf
                        top = np.argpartition(-score, shortlist - 1, axis=0)[:shortlist]
                        for j in range(len(q)):
                            some = top[score[top[:, j], j] > -np.inf, j]
                            if len(some) >= want:
                                floor[j] = np.partition(products(x[some], q[j]), len(some) - want)[len(some) - want]
                    least = floor / (far * longest)
                    least = np.where(np.isfinite(least), least - 1e-6 * np.abs(least) - 1e-37, -np.inf).astype(np.float32)
                    most = np.abs(near)
                    most -= loose[rows]
                    np.maximum(most, 0, out=most)
                    most *= most
                    np.subtract(1, most, out=most)
                    np.sqrt(np.maximum(most, 0, out=most), out=most)
                    most *= rest[rows]
                    near *= part[rows]
                    most += near
                    most += slack[rows]
                    open_ = most >= least
                    if np.count_nonzero(open_) > open_.size // 32:  # else the few are ranked exactly at once
                        about = thin[rows] @ unit.T
                        about += slack[rows]
                        open_ &= about >= least
                else:
                    open_ = np.ones((len(ids[rows]), len(q)), bool)
                r, c = np.nonzero(open_)
                other = ids[rows][r] != asked[c]
                r, c = r[other] + first, c[other]
                for at in range(0, len(r), pairs_at_once):
                    a, b = r[at : at + pairs_at_once], c[at : at + pairs_at_once]
                    exact = x[a, 0] * q[b, 0]
                    for d in range(1, x.shape[1]):
                        exact += x[a, d] * q[b, d]
                    best_of, best_id, best = np.concatenate([best_of, b]), np.concatenate([best_id, ids[a]]), np.concatenate([best, exact])
                    by = np.lexsort((best_id, -best, best_of))
                    place = np.arange(len(by)) - np.searchsorted(best_of[by], best_of[by])
                    by = by[place < want]
                    best_of, best_id, best = best_of[by], best_id[by], best[by]
                n = np.bincount(best_of, minlength=len(q))
                ends = np.cumsum(n)
                full = n >= want
                floor[full] = np.maximum(floor[full], best[ends[full] - 1])
            ends = np.concatenate([[0], np.cumsum(np.bincount(best_of, minlength=len(q)))])
            for j, qid in enumerate(asked.tolist()):
                yield qid, best_id[ends[j] : ends[j + 1]], best[ends[j] : ends[j + 1]]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []

        def flush() -> Iterator[pa.RecordBatch]:
            if not held:
                return
            found = list(scan(*(np.concatenate(x) for x in zip(*held))))
            held.clear()
            size = [len(i) for _, i, _ in found]
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat([q for q, _, _ in found], size).astype(np.int64)), pa.array(np.concatenate([i for _, i, _ in found])), pa.array(np.concatenate([s for _, _, s in found]))], names=["query_id", "vec_id", "score"])

        for batch in batches:
            if batch.num_rows:
                raw = np.frombuffer(b"".join(batch.column("codes").to_pylist()), np.uint8).reshape(batch.num_rows, -1)
                held.append((batch.column("vec_id").to_numpy(), _matrix(batch.column("v")), raw, batch.column("norm").to_numpy()))
            if sum(len(h[0]) for h in held) >= TASK_ROWS:
                yield from flush()
        yield from flush()

    near = index.mapInArrow(run, "query_id long, vec_id long, score double")
    rank = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return near.withColumn("rank", F.row_number().over(rank)).where(F.col("rank") <= want)


def search(vectors: DataFrame, is_query, want: int = 20, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): nearest rows of every row that ``is_query`` accepts."""
    spark = vectors.sparkSession
    index, books = build_index(usable(vectors, id_col, vector_col))
    empty = spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    if books is None:
        return empty
    # rows that share a query's id are one query, its smallest vector
    asked = materialise(index.where(is_query(F.col("vec_id"))).groupBy("vec_id").agg(F.min("v").alias("v")), "queries")
    blocks = -(-asked.count() // QUERY_BLOCK)
    out = empty
    for b in range(blocks):
        rows = asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b).orderBy("vec_id").collect()
        for begin in range(0, len(rows), 2 * QUERY_BLOCK):  # hashed blocks are near equal; a larger one is cut
            some = rows[begin : begin + 2 * QUERY_BLOCK]
            found = search_block(index, books, np.array([r["vec_id"] for r in some]), np.array([r["v"] for r in some]), want)
            out = out.unionByName(materialise(found.select("query_id", "rank", "vec_id", "score"), "neighbours"))
    return out
