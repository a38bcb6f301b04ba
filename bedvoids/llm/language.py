"""Language of documents by string kernels, Nyström landmarks and one-versus-rest kernel ridge regression.

Texts are lower-cased, everything but letters becomes single spaces. The kernel of two texts is the sum,
over lengths 1 to 4, of how many n-grams both hold, divided by the root of the product of both texts' own
values (presence, not counts; n-grams of bytes, hashed to a fixed number of places for each length).
Landmarks and the rows that the regression is fitted on are drawn by hash, equally from each language, and
are at most LANDMARKS and SAMPLE; only bit sets of n-grams reach the driver. All texts are scored, whole,
by products of batches with the landmarks.

Null texts and texts without a letter are `und` with score 0. Rows without language aren't learned from.
If nothing can be learned from, every text is `und`. Copies of a text are learned from once in a language; rows are
scored as they stand. Extra columns are ignored. Presence of n-grams of a text fills the fixed places as the text grows:
from about a million letters on nearly all are taken, and only how many n-grams a landmark has still tells languages apart.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import texthash as H

#: Fitted on at most so many rows, drawn by hash.
SAMPLE, LANDMARKS = 4000, 256
PLACES = (256, 2048, 4096, 4096)
RIDGE = 1e-2


def letters(column: pa.Array) -> pa.Array:
    """Lower-case words of letters between single spaces."""
    column = pc.utf8_lower(column.fill_null(""))
    return pc.replace_substring_regex(column, r"[^\pL]+", " ")


def presence(column: pa.Array) -> Iterator[tuple[int, np.ndarray]]:
    """(first row, matrix of 0 and 1) for batches of rows of a column as made by `letters`."""
    data, bounds = H.text_buffer(column)
    starts = np.r_[0, np.cumsum(PLACES)]
    for i, j in H.pieces(bounds):
        for a in range(i, j, 256):
            b = min(j, a + 256)
            part, cut = data[bounds[a] : bounds[b]], bounds[a : b + 1] - bounds[a]
            x = np.zeros((b - a, starts[-1]), np.float32)
            row = np.repeat(np.arange(b - a), np.diff(cut))
            code = np.zeros(len(part), np.uint32)
            for n, places in enumerate(PLACES, 1):
                if len(part) < n:
                    break
                code = (code[: len(part) - n + 1] << np.uint32(8)) | part[n - 1 :]
                same = row[: len(code)] == row[n - 1 :]
                h = code * np.uint32(0x9E3779B1)
                h = (h ^ (h >> np.uint32(15))) * np.uint32(0x85EBCA77)
                x[row[: len(code)][same], (starts[n - 1] + (h >> np.uint32(16)) % np.uint32(places))[same]] = 1
            yield a, x


def _bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = [np.packbits(r).tobytes() for _, x in presence(letters(batch.column("text"))) for r in x.astype(bool)]
        yield pa.RecordBatch.from_arrays([batch.column("label"), batch.column("draw"), pa.array(out, pa.binary())], names=["label", "draw", "bits"])


class Model:
    """One-versus-rest kernel ridge regression over Nyström features."""

    def __init__(self, x: np.ndarray, labels: list[str], landmarks: int = LANDMARKS):
        self.names = sorted(set(labels))
        self.land = x[:landmarks]
        self.norm = np.sqrt(self.land.sum(1))
        k = self.kernel(self.land).astype(float)
        values, vectors = np.linalg.eigh((k + k.T) / 2)
        good = values > 1e-6 * values.max()
        root = vectors[:, good] / np.sqrt(values[good])
        z = np.concatenate([self.kernel(x[i : i + 512]).astype(float) @ root for i in range(0, len(x), 512)])
        z = np.c_[z, np.ones(len(z))]
        y = np.where(np.array(labels)[:, None] == np.array(self.names)[None, :], 1.0, -1.0)
        # every language weighs the same, however many of its rows were drawn
        w = 1 / (y > 0).sum(0)[np.array([self.names.index(v) for v in labels])]
        w *= len(w) / w.sum()
        a = (z * w[:, None]).T @ z + RIDGE * len(z) / 1000 * np.eye(z.shape[1])
        coef = np.linalg.solve(a, (z * w[:, None]).T @ y)
        self.weights, self.bias = (root @ coef[:-1]).astype(np.float32), coef[-1]

    def kernel(self, x: np.ndarray) -> np.ndarray:
        own = np.sqrt(np.maximum(x.sum(1), 1))
        return (x @ self.land.T) / own[:, None] / self.norm[None, :]

    def scores(self, x: np.ndarray) -> np.ndarray:
        return self.kernel(x) @ self.weights + self.bias


def fit(rows: DataFrame, sample: int = SAMPLE) -> Model | None:
    """Learns from (text, label), at most about `sample` rows, as many from each label."""
    rows = rows.where("text is not null and label is not null").select(F.col("text"), F.col("label").cast("string"), F.shiftright(F.xxhash64("text", F.lit(5)), 1).alias("draw"))
    counts = {r["label"]: r["n"] for r in rows.groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    if not counts:
        return None
    each = max(1, sample // len(counts))
    # the part of a label's rows that holds about `each`; draws run over -2**62 to 2**62
    limit = F.create_map(*[F.lit(v) for k, n in counts.items() for v in (k, int(-(1 << 62) + min(1.0, 1.2 * each / n) * ((1 << 63) - 2)))])
    few = rows.where(F.col("draw") <= F.element_at(limit, F.col("label")))
    # copies of a text are drawn together and count once, so that no text brings all its copies along
    few = few.groupBy("label", "draw").agg(F.any_value("text").alias("text")).select("text", "label", "draw")
    drawn = few.mapInArrow(_bits, "label string, draw long, bits binary").collect()
    by: dict[str, list] = {}
    for r in sorted(drawn, key=lambda r: (r["draw"], r["label"], bytes(r["bits"]))):
        by.setdefault(r["label"], []).append(r)
    picked = [r for i in range(each) for k in sorted(by) for r in by[k][i : i + 1]]
    x = np.stack([np.unpackbits(np.frombuffer(bytes(r["bits"]), np.uint8))[: sum(PLACES)] for r in picked]).astype(np.float32)
    there = x.any(1)
    if not there.any():
        return None
    return Model(x[there], [r["label"] for r, t in zip(picked, there, strict=True) if t])


def _predict(model: Model | None):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text = letters(batch.column("text"))
            some = pc.not_equal(pc.utf8_trim_whitespace(text), "").to_numpy(zero_copy_only=False)
            names, score = np.full(batch.num_rows, "und", object), np.zeros(batch.num_rows)
            if model:
                for i, x in presence(text):
                    f = model.scores(x)
                    best = f.argmax(1)
                    at = slice(i, i + len(x))
                    names[at] = np.where(some[at], np.array(model.names, object)[best], "und")
                    score[at] = np.where(some[at], np.clip((f[np.arange(len(f)), best] + 1) / 2, 0, 1), 0)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(names.tolist(), pa.string()), pa.array(score)], names=["doc_id", "held_out", "lang_pred", "score"])

    return run


def held_out(parts: int, part: int) -> Column:
    """Whether crc32 of the id as text leaves that remainder; ids that are null are never learned from."""
    return F.coalesce(F.pmod(F.crc32(F.encode(F.col("doc_id").cast("string"), "utf-8")), F.lit(parts)) == part, F.lit(True))


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score for each row; learns from rows that aren't held out."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(4, 2).alias("held_out"), F.col("text").cast("string").alias("text"), F.col("lang").alias("label"))
    model = fit(rows.where("not held_out").select("text", "label"))
    return rows.select("doc_id", "held_out", "text").mapInArrow(_predict(model), "doc_id long, held_out boolean, lang_pred string, score double")
