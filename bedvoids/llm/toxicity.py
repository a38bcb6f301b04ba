"""Toxicity by a linear classifier over character n-grams scaled by naive Bayes log-count ratios.

Texts are lower-cased and white space runs become one space, also added at both ends; n-grams of 3 to 6
bytes count as present or absent and are hashed to PLACES places. Each place's weight in naive Bayes, the
log ratio of how often texts of either class hold it, scales it; a logistic regression with a quadratic
penalty is fitted on the scaled places and scored over whole texts.

The classifier is fitted on at most SAMPLE labelled rows of each class, drawn by hash; only compressed bit
sets reach the driver. Null and empty texts are scored like texts without n-grams. Labels for one document
that disagree count as toxic. If no label can be learned from, every score is the share of toxic labels, or
0. Repeated rows count as they stand; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import texthash as H
from .language import held_out

SAMPLE = 2000
PLACES = 1 << 18
SIZES = (3, 4, 5, 6)
#: A place counts if so many of the drawn rows hold it and its log-count ratio is this far from 0.
LEAST, APART = 8, 1.5
PENALTY = 1e-2


def plain(column: pa.Array) -> pa.Array:
    spaced = pc.replace_substring_regex(pc.utf8_lower(column.fill_null("")), r"\s+", " ")
    return pc.binary_join_element_wise(" ", pc.utf8_trim_whitespace(spaced), " ", "")


def present(column: pa.Array) -> Iterator[tuple[int, np.ndarray]]:
    """(row, its places) for each row of a column as made by `plain`."""
    data, bounds = H.text_buffer(column)
    mark = np.zeros(PLACES, bool)
    for i, j in H.pieces(bounds):
        part, cut = data[bounds[i] : bounds[j]], bounds[i : j + 1] - bounds[i]
        p = H.prefix(part)
        places = []
        for n in SIZES:
            at = np.arange(max(0, len(part) - n + 1))
            places.append((H.span(p, at, at + n) >> H.U(64 - 18)).astype(np.int32))
        for r in range(j - i):
            for n, x in zip(SIZES, places, strict=True):
                mark[x[cut[r] : max(cut[r], cut[r + 1] - n + 1)]] = True
            found = np.flatnonzero(mark)
            mark[found] = False
            yield i + r, found


def _bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = []
        for _, found in present(plain(batch.column("text"))):
            mark = np.zeros(PLACES, bool)
            mark[found] = True
            out.append(zlib.compress(np.packbits(mark).tobytes(), 1))
        yield pa.RecordBatch.from_arrays([batch.column("toxic"), batch.column("draw"), pa.array(out, pa.binary())], names=["toxic", "draw", "bits"])


def _places(bits: bytes) -> np.ndarray:
    return np.flatnonzero(np.unpackbits(np.frombuffer(zlib.decompress(bits), np.uint8)))


class Model:
    """Weights for all places, with the log-count ratios multiplied in."""

    def __init__(self, bits: list[bytes], y: np.ndarray, rounds: int = 200):
        count = [np.zeros(PLACES, np.int64), np.zeros(PLACES, np.int64)]
        for x, c in zip(bits, y, strict=True):
            count[c][_places(x)] += 1
        n = [(y == c).sum() for c in (0, 1)]
        ratio = np.log((count[1] + 1) / (n[1] + 2)) - np.log((count[0] + 1) / (n[0] + 2))
        keep = np.flatnonzero((count[0] + count[1] >= LEAST) & (np.abs(ratio) >= APART))
        if not len(keep):  # very few labels
            keep = np.flatnonzero(ratio)
        place = np.full(PLACES, -1, np.int32)
        place[keep] = np.arange(len(keep))
        # one row at a time: only its places that count are held
        rows = [p[p >= 0] for p in (place[_places(x)] for x in bits)]
        idx, row, size = np.concatenate(rows), np.repeat(np.arange(len(rows)), [len(r) for r in rows]), len(keep)
        scale = ratio[keep][idx]
        cost = np.where(y == 1, 0.5 / n[1], 0.5 / n[0])  # both classes weigh the same
        w, b = np.zeros(size), 0.0
        # gradient steps with running means of the gradient and of its square
        m, v, mb, vb = np.zeros(size), np.zeros(size), 0.0, 0.0
        for t in range(1, rounds + 1):
            f = np.bincount(row, scale * w[idx], minlength=len(y)) + b
            g = (1 / (1 + np.exp(-np.clip(f, -30, 30))) - y) * cost
            gw = np.bincount(idx, scale * g[row], minlength=size) + PENALTY * w
            gb = g.sum()
            m, v, mb, vb = 0.9 * m + 0.1 * gw, 0.99 * v + 0.01 * gw * gw, 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb * gb
            rate = 0.05 * (1 - t / (rounds + 1))
            w -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
            b -= rate * (mb / (1 - 0.9**t)) / (np.sqrt(vb / (1 - 0.99**t)) + 1e-8)
        self.weights = np.zeros(PLACES, np.float32)
        self.weights[keep] = w * ratio[keep]
        self.bias = float(b)

    def score(self, found: np.ndarray) -> float:
        return float(1 / (1 + np.exp(-np.clip(self.weights[found].sum(dtype=float) + self.bias, -30, 30))))


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model | float:
    """Learns from labels that aren't held out; where there is only one class, its share of them."""
    marks = labels.where("toxic is not null").where(~held_out(5, 0)).groupBy(F.col("doc_id").cast("long").alias("_id")).agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    marks = marks.withColumn("draw", F.shiftright(F.xxhash64("_id", F.lit(7)), 1))
    n = {r["toxic"]: r["n"] for r in marks.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    if len(n) < 2:
        return float(1 in n)
    limit = F.create_map(*[F.lit(v) for k, c in n.items() for v in (k, int(-(1 << 62) + min(1.0, 1.1 * sample / c) * ((1 << 63) - 2)))])
    # about 1.1 * sample ids of each class: small whatever the tables, so no text has to move
    few = marks.where(F.col("draw") <= F.element_at(limit, F.col("toxic")))
    texts = docs.select(F.col("doc_id").cast("long").alias("_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(few), "_id")
    drawn = texts.select("text", "toxic", "draw").mapInArrow(H.tidy(_bits), "toxic int, draw long, bits binary").collect()
    drawn.sort(key=lambda r: (r["toxic"], r["draw"], bytes(r["bits"])))
    picked = [r for c in (0, 1) for r in [x for x in drawn if x["toxic"] == c][:sample]]
    y = np.array([r["toxic"] for r in picked])
    if len(np.unique(y)) < 2:
        return float(n.get(1, 0) / sum(n.values()))
    return Model([bytes(r["bits"]) for r in picked], y)


def _score(model: Model | float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            score = np.full(batch.num_rows, model if isinstance(model, float) else 0.0)
            if not isinstance(model, float):
                for r, found in present(plain(batch.column("text"))):
                    score[r] = model.score(found)
            cols = [batch.column(c) for c in batch.schema.names if c != "text"]
            names = [c for c in batch.schema.names if c != "text"]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(score), pa.array((score >= 0.5).astype(np.int32))], names=[*names, "score", "predicted"])

    return run


def scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted for each row of `docs`."""
    model = fit(docs, labels)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(5, 0).alias("held_out"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(H.tidy(_score(model)), "doc_id long, held_out boolean, score double, predicted int")


def without_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """`docs` without those predicted toxic."""
    model = fit(docs, labels)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = next(_score(model)(iter([batch.select(["text"])]))).column("predicted")
            yield batch.filter(pc.equal(got, 0))

    return docs.mapInArrow(H.tidy(run), docs.schema)
