"""Embedding near-dedup by product quantisation.

Equal vectors of one label form a class first, so copies cost one row.  Coarse
inverted lists hold classes by nearest centroid, as many lists as the root of
the number of classes; residuals are coded by subspace.  A label's lists are
packed into units of some thousand rows, a large list into several.  A vector
probes every list that can hold a partner: the plane midway between its own
centroid and the list's is no further from it than the linking distance, so no
link is lost.  Units meet where one probes a list that the other holds; a task
takes a unit and a bounded number of those that it meets.  There,
asymmetric table-lookup distances, less each code's known error, discard what
cannot be near, and an exact cosine in double precision decides the rest.
Tasks return counts and spanning edges.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from arcfield.deploy import save, ship
from arcfield.operators.components import components
from arcfield.llm.simhash import _fold

#: The quantiser is fitted on at most this many classes, chosen by hash; a centroid needs so many of them.
FIT_SAMPLE, LEAST_FIT = 20_000, 16
SUBSPACES, CODES = 8, 64
#: Rows of a unit, and units that a task compares its own with.
UNIT_ROWS, PARTNERS = 2048, 16
_SLACK = 1e-9


@dataclass(frozen=True)
class Quantiser:
    centroids: np.ndarray  # lists x d
    books: np.ndarray  # subspaces x codes x d/subspaces (d padded)
    gaps: np.ndarray  # distances between centroids

    def pad(self, x: np.ndarray) -> np.ndarray:
        width = self.books.shape[0] * self.books.shape[2]
        return x if x.shape[1] == width else np.hstack((x, np.zeros((len(x), width - x.shape[1]))))

    def assign(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Squared distances to all centroids and the nearest list."""
        d = np.maximum(0.0, (x * x).sum(1)[:, None] + (self.centroids * self.centroids).sum(1)[None] - 2 * x @ self.centroids.T)
        return d, d.argmin(1)

    def probes(self, x: np.ndarray, delta: float) -> tuple[np.ndarray, np.ndarray]:
        """Nearest list of each vector, and the lists that may hold a vector within ``delta`` of it."""
        d, home = self.assign(x)
        return home, d - d[np.arange(len(d)), home][:, None] <= 2 * delta * self.gaps[home] + _SLACK

    def encode(self, x: np.ndarray, home: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Codes of the residuals, each vector's distance to its coded form, and that form's squared length."""
        parts = self.pad(x - self.centroids[home]).reshape(len(x), self.books.shape[0], -1)
        codes = np.empty((len(x), self.books.shape[0]), np.uint8)
        near = self.pad(self.centroids[home]).reshape(parts.shape).copy()
        err = np.zeros(len(x))
        for m, book in enumerate(self.books):
            d = ((parts[:, m, None, :] - book[None]) ** 2).sum(2)
            codes[:, m] = d.argmin(1)
            err += d.min(1)
            near[:, m] += book[codes[:, m]]
        return codes, np.sqrt(err), (near * near).sum((1, 2))

    def tables(self, x: np.ndarray) -> np.ndarray:
        """Inner product of each query's subspaces with each code: subspaces x queries x codes."""
        parts = self.pad(x).reshape(len(x), self.books.shape[0], -1)
        return np.einsum("qmk,mck->mqc", parts, self.books)


def _kmeans(x: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 12) -> np.ndarray:
    c = x[rng.choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        at = ((c * c).sum(1)[None] - 2 * x @ c.T).argmin(1)
        n = np.bincount(at, minlength=k)
        total = np.zeros_like(c)
        np.add.at(total, at, x)
        c[n > 0] = total[n > 0] / n[n > 0, None]
    return c


def fit(sample: np.ndarray, lists: int) -> Quantiser:
    rng = np.random.default_rng(3)
    lists = max(1, min(lists, len(sample)))
    centroids = _kmeans(sample, lists, rng)
    # lists by their place along the main axis of the centroids, so that units hold near ones
    centred = centroids - centroids.mean(0)
    centroids = centroids[np.argsort(centred @ np.linalg.svd(centred, full_matrices=False)[2][0], kind="stable")]
    gaps = np.stack([np.sqrt(((centroids - c) ** 2).sum(1)) for c in centroids])
    q = Quantiser(centroids, np.zeros((SUBSPACES, 1, -(-sample.shape[1] // SUBSPACES))), gaps)
    _, at = q.assign(sample)
    parts = q.pad(sample - centroids[at]).reshape(len(sample), SUBSPACES, -1)
    return Quantiser(centroids, np.stack([_kmeans(parts[:, m], min(CODES, len(sample)), rng, 8) for m in range(SUBSPACES)]), gaps)


def _matrix(column: pd.Series) -> np.ndarray:
    return np.stack([np.asarray(v, np.float64) for v in column]) if len(column) else np.zeros((0, 1))


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x * x).sum(1))[:, None]


def search(q: Quantiser, x: np.ndarray, y: np.ndarray, limit: float, *, same: bool) -> tuple[np.ndarray, np.ndarray, int]:
    """Index pairs (u, v) of rows of ``x`` and ``y`` with a cosine of ``limit`` or more, and how many the codes let through.

    With ``same`` both are one unit and a row is not paired with itself.
    """
    delta = float(np.sqrt(max(0.0, 2 - 2 * limit))) + _SLACK
    ux, uy, nx, ny = _unit(x), _unit(y), np.sqrt((x * x).sum(1)), np.sqrt((y * y).sum(1))
    _, probes = q.probes(ux, delta)
    home = q.assign(uy)[1]
    order = np.argsort(home, kind="stable")
    codes, err, length = q.encode(uy[order], home[order])
    cuts = np.searchsorted(home[order], np.arange(len(q.centroids) + 1))
    tables, to_centre = q.tables(ux), ux @ q.centroids.T
    found, passed = [], 0
    for c in np.flatnonzero(np.diff(cuts)):
        members = slice(cuts[c], cuts[c + 1])
        asking = np.flatnonzero(probes[:, c])
        for at in range(0, len(asking), 1024):
            u = asking[at : at + 1024]
            inner = to_centre[u, c][:, None] + sum(tables[m][u][:, codes[members, m]] for m in range(len(tables)))
            bound = (delta + err[members]) ** 2 + _SLACK
            i, j = np.nonzero(1.0 + length[members][None] - 2 * inner <= bound[None])
            i, j = u[i], order[members][j]
            if same:
                i, j = i[i != j], j[i != j]
            passed += len(i)
            near = np.einsum("ij,ij->i", x[i], y[j]) / (nx[i] * ny[j]) >= limit
            found.append((i[near], j[near]))
    u, v = (np.concatenate(k) for k in zip(*found)) if found else (np.zeros(0, np.int64),) * 2
    return u, v, passed


def near_links(classes: DataFrame, q: Quantiser, limit: float) -> DataFrame:
    """(cid, links, tied): per visited class the vectors linked to it there, and a spanning edge or null.

    ``classes``: cid, label, copies, embedding; distinct, usable, of one length.
    """
    spark = classes.sparkSession
    ship(spark)
    delta = float(np.sqrt(max(0.0, 2 - 2 * limit))) + _SLACK
    sent = spark.sparkContext.broadcast(q)

    def home(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            if len(pdf):
                yield pd.DataFrame({"cid": pdf["cid"], "label": pdf["label"], "list": sent.value.assign(_unit(_matrix(pdf["embedding"])))[1].astype(np.int32)})

    spots = save(classes.select("cid", "label", "embedding").mapInPandas(home, "cid long, label long, list int"), "spots")
    # a label's lists in turn fill its units; what is too many for one is salted
    before = W.partitionBy("label").orderBy("list").rowsBetween(W.unboundedPreceding, -1)
    cells = spots.groupBy("label", "list").agg(F.count("*").alias("n")).withColumn("unit", F.floor(F.coalesce(F.sum("n").over(before), F.lit(0)) / UNIT_ROWS))
    cells = cells.withColumn("parts", F.ceil(F.sum("n").over(W.partitionBy("label", "unit")) / UNIT_ROWS)).drop("n")
    dealt = spots.join(cells, ["label", "list"]).select("cid", "unit", F.pmod(F.xxhash64("cid"), F.col("parts")).alias("salt"))

    def pack(pdf: pd.DataFrame) -> pd.DataFrame:
        q, pdf = sent.value, pdf.sort_values("cid")
        x = _matrix(pdf["embedding"])
        held, asked = np.zeros(len(q.centroids), bool), np.zeros(len(q.centroids), bool)
        for at in range(0, len(x), 256):
            own, probes = q.probes(_unit(x[at : at + 256]), delta)
            held[own] = True
            asked |= probes.any(0)
        row = {"label": pdf["label"].iloc[0], "holds": np.flatnonzero(held).tolist(), "asks": np.flatnonzero(asked).tolist()}
        return pd.DataFrame([row | {"cids": pdf["cid"].to_numpy(np.int64).tobytes(), "copies": pdf["copies"].to_numpy(np.int64).tobytes(), "x": x.tobytes()}])

    packed = classes.join(dealt, "cid").groupBy("label", "unit", "salt").applyInPandas(pack, "label long, holds array<int>, asks array<int>, cids binary, copies binary, x binary")
    units = save(packed.withColumn("no", F.monotonically_increasing_id()), "vector-units")
    asking = units.select("label", F.col("no").alias("a"), F.explode("asks").alias("list"))
    holding = units.select("label", F.col("no").alias("b"), F.explode("holds").alias("list"))
    # a link lies in lists that both ends probe, so one order of each pair is enough
    met = save(asking.join(holding, ["label", "list"]).where("a <= b").select("a", "b").distinct(), "vector-meetings")
    turn = F.pmod(F.xxhash64("a", "b"), F.lit(2)) == 0
    met = met.select(F.when(turn, F.col("a")).otherwise(F.col("b")).alias("own"), F.when(turn, F.col("b")).otherwise(F.col("a")).alias("no"))
    met = met.withColumn("chunk", F.floor(F.col("no") / PARTNERS))
    mine = met.select("own", "chunk").distinct().select("own", "chunk", F.lit(True).alias("is_own"), F.col("own").alias("no"))
    visits = mine.unionByName(met.select("own", "chunk", F.lit(False).alias("is_own"), "no")).join(units.select("no", "cids", "copies", "x"), "no")
    n = max(int(spark.conf.get("spark.sql.shuffle.partitions")), met.count() * UNIT_ROWS * q.centroids.shape[1] * 8 >> 27)

    def meet(pdf: pd.DataFrame) -> pd.DataFrame:
        q, pdf = sent.value, pdf.sort_values(["is_own", "no"])
        rows = [(r.no, np.frombuffer(r.cids, np.int64), np.frombuffer(r.copies, np.int64), np.frombuffer(r.x, np.float64)) for r in pdf.itertuples()]
        no, ca, na, x = rows.pop()
        x = x.reshape(len(ca), -1)
        every = np.unique(np.concatenate([r[1] for r in rows] + [ca]))
        label, links, ia = np.arange(len(every)), np.zeros(len(every), np.int64), np.searchsorted(every, ca)
        for other, cb, nb, y in rows:
            u, v, _ = search(q, x, y.reshape(len(cb), -1), limit, same=other == no)
            ib = np.searchsorted(every, cb)
            np.add.at(links, ia[u], nb[v])
            if other != no:
                np.add.at(links, ib[v], na[u])
            _fold(label, ia[u], ib[v])
        some = (links > 0) | (label != np.arange(len(every)))
        tied = pd.array(every[label], "Int64")
        tied[label == np.arange(len(every))] = pd.NA
        return pd.DataFrame({"cid": every[some], "links": links[some], "tied": tied[some]})

    return visits.repartition(n, "own", "chunk").groupBy("own", "chunk").applyInPandas(meet, "cid long, links long, tied long")


def usable(column: str = "embedding"):
    """True for a vector without null or non-finite components and not all zero."""
    v = F.col(column)
    fine = F.forall(v, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) < float("inf")))
    return F.coalesce(v.isNotNull() & (F.size(v) > 0) & fine & F.exists(v, lambda e: e != 0), F.lit(False))


def dedup_vectors(vectors: DataFrame, limit: float = 0.98, lists: int | None = None) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every row.

    Links join rows of one non-null label whose cosine, in double precision, is
    ``limit`` or more.  Null, zero, empty and non-finite vectors and null
    labels link with nothing and are their own component; vectors of unlike
    length never link.  Repeated vectors link with each other, whatever their
    ids; a repeated id with other vectors is another row, judged by its own
    vector.  A null id links with nothing.  Other columns are not read; an empty
    table gives no rows.
    """
    spark = vectors.sparkSession
    rows = vectors.select("vec_id", F.col("label").cast("long").alias("label"), "embedding")
    ok = F.col("label").isNotNull() & usable() & F.col("vec_id").isNotNull()
    # ids may repeat: classes have a number of their own
    classes = rows.where(ok).groupBy("label", "embedding").agg(F.min("vec_id").alias("first_id"), F.count("*").alias("copies"))
    classes = save(classes.withColumn("cid", F.monotonically_increasing_id()), "vector-classes")
    # vectors of unlike length never meet
    lengths = {r[0]: r[1] for r in classes.groupBy(F.size("embedding")).count().collect()}
    found = None
    for length, n in lengths.items():
        own = classes.where(F.size("embedding") == length)
        sample = own.orderBy(F.xxhash64("cid")).limit(FIT_SAMPLE).select("embedding").toPandas()
        q = fit(_unit(_matrix(sample["embedding"])), lists or max(1, min(int(n**0.5), len(sample) // LEAST_FIT)))
        part = near_links(own, q, limit)
        found = part if found is None else found.unionByName(part)
    if found is None:
        found = spark.createDataFrame([], "cid long, links long, tied long")
    found = save(found, "vector-links")
    tied = components(found.where("tied is not null"), "cid", "tied")
    counts = found.groupBy("cid").agg(F.sum("links").alias("links"))
    named = classes.join(counts, "cid", "left").join(tied, F.col("cid") == F.col("node"), "left").withColumn("root", F.coalesce("root", "cid"))
    named = save(named.select("label", "embedding", "first_id", "root", (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links")), "vector-named")
    names = named.groupBy("root").agg(F.min("first_id").alias("component_id"))
    named = named.join(names, "root").select(F.col("label").alias("l"), F.col("embedding").alias("e"), "n_links", "component_id")
    joined = rows.where(ok).join(named, (F.col("label") == F.col("l")) & (F.col("embedding") == F.col("e"))).select("vec_id", "n_links", "component_id")
    alone = rows.where(~ok).select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return joined.unionByName(alone).withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


ORACLE = """
WITH RECURSIVE good AS (
  SELECT vec_id, label, embedding::DOUBLE[] AS v FROM embeddings
  WHERE label IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda e: e IS NULL OR NOT isfinite(e))) = 0 AND len(list_filter(embedding, lambda e: e <> 0)) > 0
), links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM good a JOIN good b ON a.label = b.label AND a.vec_id <> b.vec_id
  WHERE list_inner_product(a.v, b.v) / (sqrt(list_inner_product(a.v, a.v)) * sqrt(list_inner_product(b.v, b.v))) >= 0.98
), reach AS (
  SELECT vec_id AS a, vec_id AS b FROM embeddings
  UNION
  SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a
), roots AS (SELECT a AS vec_id, min(b) AS component_id FROM reach GROUP BY a)
SELECT e.vec_id, (SELECT count(*) FROM links WHERE a = e.vec_id) AS n_links, component_id, e.vec_id = component_id AS kept
FROM embeddings e JOIN roots USING (vec_id)
"""
