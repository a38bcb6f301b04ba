"""Near-duplicate documents by one-permutation MinHash.

One hash per shingle fills all bins of a signature: its upper part picks the bin, its lower part competes
for the bin's minimum. Empty bins take the value of a filled one, picked by a hash of the bin's number
and the attempt (optimal densification), so sparse documents agree in a bin as often as their similarity
says. Bins are read in bands; documents that agree in a band share a bucket.

Documents with the same shingle set are first reduced to one, which is a node. In each bucket every member is
compared only with the bucket's smallest node (a star), on full shingle sets. Links
that no star shows can only matter where a bucket still holds members of different groups: there stars
around other members follow, and in the end all pairs across groups that haven't been compared, but for those
that a bound on their common shingles rules out, so no link between groups is lost to the stars. Stars are
dealt to several tasks, and a task holds one hub's set at a time. Buckets are found, and shingles that several
documents have, by one shuffle each: rows of a key stand together and pass by one after the other.

Null and empty texts have no shingles: they link with nothing, and neither do rows without id. Texts of fewer
than `k` words have one shingle of all of them. Groups are of texts: rows that share an id are in one group only if
their texts are linked. Extra columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import texthash as H
from .store import components, discard, store

#: A pair at similarity 0.8 misses all bands with probability (1 - 0.8 ** 7) ** 48, about 1 in 80,000.
BANDS, ROWS = 48, 7
#: Rounds of stars around drawn members, before the pairs across groups that are left are compared one by one.
TURNS = 1
#: Shingles are counted in so many parts to bound how many two documents can have in common.
PARTS = 64
#: A star is dealt to so many tasks at most, one for so many partners.
SALT, SHARE = 16, 64
#: All pairs of a bucket are dealt by pairs of blocks of about so many members.
BLOCK = 512


def densified(sign: np.ndarray) -> np.ndarray:
    """Signatures (documents x bins, largest value = empty) with each empty bin filled from a filled one."""
    empty = ~H.U(0)
    n, bins = sign.shape
    out = sign.copy()
    filled = sign != empty
    row, col = np.nonzero(~filled)
    attempt = 0
    while len(row):
        attempt += 1
        source = (H.mix(col.astype(H.U) * H.U(0x9E3779B97F4A7C15) + H.U(attempt)) % H.U(bins)).astype(np.int64)
        ready = filled[row, source]
        out[row[ready], col[ready]] = H.mix(sign[row[ready], source[ready]] + H.U(attempt))
        row, col = row[~ready], col[~ready]
    return out


def signatures(rows: np.ndarray, values: np.ndarray, n: int, bins: int) -> np.ndarray:
    """One-permutation signatures of n shingle sets (rows sorted)."""
    sign = np.full((n, bins), ~H.U(0), H.U)
    if len(rows):
        h = H.mix(values ^ H.U(0x5851F42D4C957F2D))
        # bin from the upper 32 bits; the rest of the hash competes
        at = rows * bins + ((h >> H.U(32)) * H.U(bins) >> H.U(32)).astype(np.int64)
        low = H.mix(h) >> H.U(1)
        order = np.lexsort((low, at))
        at, low = at[order], low[order]
        first = np.r_[True, at[1:] != at[:-1]]
        sign.reshape(-1)[at[first]] = low[first]
    return sign


def set_hash(rows: np.ndarray, values: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    out = []
    for salt in (0x1234567, 0x89ABCDE):
        total = np.zeros(n, H.U)
        np.add.at(total, rows, H.mix(values + H.U(salt)))
        out.append(total)
    return out[0], out[1]


def _emit_signatures(k: int, bands: int, width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, bounds = H.text_buffer(batch.column("text"))
            ids, marks = batch.column("doc_id"), batch.column("mark")
            for i, j in H.pieces(bounds):
                m = j - i
                rows, values = H.distinct(*H.shingles(data[bounds[i] : bounds[j]], bounds[i : j + 1] - bounds[i], k))
                count = np.bincount(rows, minlength=m)
                x, y = set_hash(rows, values, m)
                keys = np.zeros((m, bands), H.U)
                for a in range(0, m, 512):
                    b = min(m, a + 512)
                    part = slice(*np.searchsorted(rows, [a, b]))
                    there = np.flatnonzero(count[a:b]) + a
                    if len(there):
                        place = np.zeros(b - a, np.int64)
                        place[there - a] = np.arange(len(there))
                        sign = densified(signatures(place[rows[part] - a], values[part], len(there), bands * width)).reshape(len(there), bands, width)
                        key = np.full((len(there), bands), H.U(7)) + np.arange(bands, dtype=H.U)
                        for c in range(width):
                            key = H.mix(key * H.U(0x100000001B3) + sign[:, :, c])
                        keys[there] = key
                lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(np.where(count > 0, bands, 0))].astype(np.int32)), H.longs(keys[count > 0].reshape(-1)))
                yield pa.RecordBatch.from_arrays([ids.slice(i, m), marks.slice(i, m), pa.array(count.astype(np.int64)), H.longs(x), H.longs(y), lists], names=["doc_id", "mark", "n", "x", "y", "bands"])

    return run


def repeated(batches: Iterator[pa.RecordBatch], by: str) -> Iterator[pa.RecordBatch]:
    """Of rows in the order of `by`: those whose value stands more than once. Only the last row waits for the next batch."""
    held = last = None
    for batch in batches:
        if not batch.num_rows:
            continue
        if held is not None:
            batch = pa.concat_batches([held, batch])
        values = batch.column(by).to_numpy()
        same = np.r_[last is not None and values[0] == last, values[1:] == values[:-1]].astype(bool)
        yield batch.slice(0, len(values) - 1).filter(pa.array(same[:-1] | same[1:]))
        held, last = batch.slice(len(values) - 1), values[-2] if len(values) > 1 else last
    if held is not None and last is not None and held.column(by)[0].as_py() == last:
        yield held


def _emit_members(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows in the order of (key, rep): those of keys that several nodes have, with the smallest of these."""
    key = hub = hub_n = 0
    for batch in repeated(batches, "key"):
        if not batch.num_rows:
            continue
        keys, reps, n = (batch.column(c).to_numpy() for c in ("key", "rep", "n"))
        # a key that goes on from the batch before keeps its hub; sets of nodes have a size, so 0 means none yet
        new = np.r_[hub_n == 0 or keys[0] != key, keys[1:] != keys[:-1]].astype(bool)
        at = np.cumsum(new)
        hubs, hubs_n = np.r_[hub, reps[new]][at], np.r_[hub_n, n[new]][at]
        key, hub, hub_n = keys[-1], hubs[-1], hubs_n[-1]
        yield pa.RecordBatch.from_arrays([batch.column("key"), batch.column("rep"), batch.column("n"), pa.array(hubs), pa.array(hubs_n)], names=["key", "rep", "n", "hub", "hub_n"])


def _emit_sets(k: int):
    """Shingle sets, sorted, of the texts whose set has the given hash; rows of one node stand together and count once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last = None
        for batch in batches:
            rep = batch.column("rep").to_numpy()
            new = np.r_[rep[:1] != last if last is not None else np.ones(len(rep[:1]), bool), rep[1:] != rep[:-1]]
            last = rep[-1] if len(rep) else last
            batch = batch.filter(pa.array(new))
            data, bounds = H.text_buffer(batch.column("text"))
            ids, want = batch.column("rep"), batch.column("x").to_numpy().view(H.U)
            for i, j in H.pieces(bounds):
                rows, values = H.distinct(*H.shingles(data[bounds[i] : bounds[j]], bounds[i : j + 1] - bounds[i], k))
                x, _ = set_hash(rows, values, j - i)
                ends = np.r_[0, np.cumsum(np.bincount(rows, minlength=j - i))] * 8
                out = H.binary(values.view(np.uint8), ends)
                keep = pa.array(np.flatnonzero(x == want[i:j]))
                yield pa.RecordBatch.from_arrays([ids.slice(i, j - i).take(keep), out.take(keep), batch.column("tasks").slice(i, j - i).take(keep)], names=["rep", "words", "tasks"])

    return run


def _emit_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for rep, words in zip(batch.column("rep").to_pylist(), batch.column("words"), strict=True):
            values = np.frombuffer(words.as_buffer(), np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(values), rep)), pa.array(values)], names=["rep", "word"])


def _emit_shared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows in the order of words: node and part of each word that stands more than once."""
    for batch in repeated(batches, "word"):
        part = (batch.column("word").to_numpy() % PARTS).astype(np.int32)
        yield pa.RecordBatch.from_arrays([batch.column("rep"), pa.array(part)], names=["rep", "part"])


def _links(percent: int):
    """A hub's set (side 0), then its partners' sets: those with 100 * intersection >= percent * union."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hub = None
        for batch in batches:
            out = []
            for a, side, b, words in zip(*(batch.column(c).to_pylist() for c in ("a", "side", "b")), batch.column("words"), strict=True):
                values = np.frombuffer(words.as_buffer(), H.U)
                if side == 0:
                    hub = values.copy()
                    continue
                both = np.concatenate([hub, values])
                both.sort()
                common = int((both[1:] == both[:-1]).sum())
                if 100 * common >= percent * (len(both) - common):
                    out.append((a, b))
            p, q = zip(*out, strict=True) if out else ((), ())
            yield pa.RecordBatch.from_arrays([pa.array(p, pa.int64()), pa.array(q, pa.int64())], names=["a", "b"])

    return run


def bounded(part: pa.Table, percent: int) -> tuple[np.ndarray, np.ndarray]:
    """Of a pair of blocks (i, j): the pairs of nodes from different groups that neither sizes nor counts of common shingles rule out."""
    i, j = part["i"][0].as_py(), part["j"][0].as_py()
    at, rep, n, g = (part[x].to_numpy() for x in ("at", "rep", "n", "g"))
    counts = part["c"].combine_chunks().flatten().to_numpy().reshape(-1, PARTS)
    left, right = np.flatnonzero(at == i), np.flatnonzero(at == j)
    out = [(rep[:0], rep[:0])]
    for a in range(0, len(left), 256):
        x = left[a : a + 256]
        open_ = g[x, None] != g[right]
        open_ &= np.minimum(n[x, None], n[right]) * 100 >= np.maximum(n[x, None], n[right]) * percent
        if i == j:
            open_ &= rep[x, None] < rep[right]
        u, v = np.nonzero(open_)
        for k in range(0, len(u), 1 << 14):
            p, q = x[u[k : k + (1 << 14)]], right[v[k : k + (1 << 14)]]
            common = np.minimum(counts[p], counts[q]).sum(1, dtype=np.int64)
            enough = common * (100 + percent) >= (n[p] + n[q]) * percent
            out.append((rep[p[enough]], rep[q[enough]]))
    p, q = (np.concatenate(x) for x in zip(*out, strict=True))
    return np.minimum(p, q), np.maximum(p, q)


def _bounded(percent: int):
    """Rows in the order of (key, i, j): the pairs of each pair of blocks."""

    def solve(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        a, b = bounded(pa.Table.from_batches(held), percent)
        return pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        last = None
        for batch in batches:
            if not batch.num_rows:
                continue
            cell = np.stack([batch.column(x).to_numpy() for x in ("key", "i", "j")])
            cuts = np.r_[0, np.flatnonzero((cell[:, 1:] != cell[:, :-1]).any(0)) + 1, batch.num_rows]
            for lo, hi in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                if held and cell[:, lo].tolist() != last:
                    yield solve(held)
                    held = []
                held.append(batch.slice(lo, hi - lo))
                last = cell[:, lo].tolist()
        if held:
            yield solve(held)

    return run


def among(rows: DataFrame, on: list[str], asked: DataFrame) -> DataFrame:
    """`rows` but most of those whose `on` isn't in `asked`: a bitmap of hashes, eight bits or more for one asked for, is sent to all."""
    bits = 1 << max(6, (8 * asked.count()).bit_length())
    place = F.pmod(F.xxhash64(*on), F.lit(bits)).alias("place")
    words = asked.select(place).groupBy(F.shiftright("place", 6).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(place & 63 as int))")).alias("bits"))
    there = rows.select("*", place).join(F.broadcast(words), F.shiftright("place", 6) == F.col("w"))
    return there.where("shiftright(bits, cast(place & 63 as int)) & 1 = 1").select(rows.columns)


def likely(texts: DataFrame, asked: DataFrame) -> DataFrame:
    """Texts that may be the head of one asked for, so that the others aren't shuffled."""
    return among(texts, ["doc_id", "mark"], asked.select("head.doc_id", "head.mark"))


def addressed(pairs: DataFrame) -> DataFrame:
    """Pairs (a, b) -> (rep, a, salt, side): a row for each task that needs a node's set, a hub's (side 0) in one for every SHARE partners."""
    tasks_of = pairs.groupBy("a").agg(F.least(F.lit(SALT), F.ceil(F.count(F.lit(1)) / SHARE)).alias("of"))
    dealt = pairs.join(tasks_of, "a").select("a", "b", F.pmod(F.xxhash64("b"), "of").cast("int").alias("salt"))
    hubs = dealt.select("a", "salt").distinct().select(F.col("a").alias("rep"), "a", "salt", F.lit(0).alias("side"))
    return hubs.unionByName(dealt.select(F.col("b").alias("rep"), "a", "salt", F.lit(1).alias("side")))


def _grouped(docs: DataFrame, k: int, percent: int, bands: int, width: int) -> tuple[DataFrame, DataFrame]:
    """Rows (doc_id, mark, n, x, y), and sets (x, y, n, head, least): the smallest (doc_id, mark) of a set and of its group."""
    tasks = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("mark"), "text")
    signed = store(texts.mapInArrow(H.tidy(_emit_signatures(k, bands, width)), "doc_id long, mark long, n long, x long, y long, bands array<long>"), "signatures")
    banded = signed.where("n > 0 and doc_id is not null").groupBy("x", "y", "n").agg(F.min(F.struct("doc_id", "mark")).alias("head"), F.any_value("bands").alias("bands"))
    banded = store(banded.withColumn("rep", F.monotonically_increasing_id()), "banded")
    signs = store(signed.drop("bands"), "rows")
    discard(signed)  # bands take most of the room

    # one shuffle finds the buckets of several nodes, and their hubs
    entries = banded.select("rep", "n", F.explode("bands").alias("key")).repartition(tasks, "key").sortWithinPartitions("key", "rep")
    members = store(entries.mapInArrow(H.tidy(_emit_members), "key long, rep long, n long, hub long, hub_n long"), "members")
    reps = store(banded.drop("bands"), "sets")
    discard(banded)
    fits = lambda p, q: F.least(p, q) * 100 >= F.greatest(p, q) * percent
    star = members.where("rep <> hub").where(fits(F.col("n"), F.col("hub_n")))
    star = store(star.select(F.col("hub").alias("a"), F.col("rep").alias("b")).distinct(), "star")

    # sets know which tasks their stars need them in (a node is in one star for each band at most), so they go there from where they are made
    sent = addressed(star).groupBy("rep").agg(F.collect_list(F.struct("a", "salt", "side")).alias("tasks"))
    asked = store(members.select("rep").distinct().join(reps.select("rep", "x", "head"), "rep").join(sent, "rep", "left"), "asked")
    there = likely(texts, asked).join(asked, (F.col("doc_id") == F.col("head.doc_id")) & (F.col("mark") == F.col("head.mark")))
    sets = there.select("rep", "x", "tasks", "text").mapInArrow(H.tidy(_emit_sets(k)), "rep long, words binary, tasks array<struct<a: long, salt: int, side: int>>")
    sets = store(sets, "words")

    def compared(dealt: DataFrame) -> DataFrame:
        dealt = dealt.repartition(tasks, "a", "salt").sortWithinPartitions("a", "salt", "side")
        return dealt.select("a", "side", F.col("rep").alias("b"), "words").mapInArrow(H.tidy(_links(percent)), "a long, b long")

    def confirmed(pairs: DataFrame) -> DataFrame:
        sent = store(addressed(pairs), "sent")
        named = among(sets.select("rep", "words"), ["rep"], sent.select("rep").distinct())
        return compared(sent.join(named, "rep"))

    links, tested = store(compared(sets.select("rep", "words", F.explode("tasks").alias("to")).select("rep", "words", "to.*")), "links"), star
    final = components(links).select(F.col("node").alias("rep"), "component")
    for turn in range(TURNS + 1):
        # buckets that still hold several groups: only pairs across groups matter, and of them only new ones
        named = members.join(final, "rep", "left").select("key", "rep", "n", F.coalesce("component", "rep").alias("g"))
        hub = F.min_by(F.struct("rep", "n", "g"), F.xxhash64("rep", "key", F.lit(turn))).alias("hub")
        open_ = named.groupBy("key").agg(F.min("g").alias("g0"), F.max("g").alias("g1"), hub, F.count(F.lit(1)).alias("m")).where("g0 <> g1").select("key", "hub", "m")
        rest = store(named.join(open_, "key"), "open")
        if turn < TURNS:  # stars around other members, drawn anew for each bucket
            pairs = rest.select(F.col("hub.rep").alias("p"), F.col("rep").alias("q"), F.col("hub.n").alias("n_p"), F.col("n").alias("n_q"), F.col("hub.g").alias("g_p"), F.col("g").alias("g_q")).where("g_p <> g_q")
            pairs = pairs.where(fits(F.col("n_p"), F.col("n_q"))).select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"))
        else:  # whatever is left, all of it; shingles that no other of these documents has can't be common to two
            # (sets that only seem to be among them can make the bound looser, never too tight)
            words = among(sets.select("rep", "words"), ["rep"], rest.select("rep").distinct()).mapInArrow(H.tidy(_emit_words), "rep long, word long")
            shared = words.repartition(tasks, "word").sortWithinPartitions("word").mapInArrow(H.tidy(_emit_shared), "rep long, part int")
            each = shared.groupBy("rep", "part").agg(F.count(F.lit(1)).cast("int").alias("c"))
            parts = each.groupBy("rep").agg(F.map_from_entries(F.collect_list(F.struct("part", "c"))).alias("counts"))
            parts = parts.select("rep", F.transform(F.sequence(F.lit(0), F.lit(PARTS - 1)), lambda i: F.coalesce(F.try_element_at("counts", i), F.lit(0))).alias("c"))
            rest = rest.join(parts, "rep")  # without shared shingles there is no partner
            # a bucket of many members is dealt to several tasks: each pair of its blocks is a piece of work of its own
            blocks = F.ceil(F.col("m") / BLOCK).cast("int")
            dealt = rest.withColumn("at", F.pmod(F.xxhash64("rep"), blocks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
            dealt = dealt.select("key", F.least("at", "other").alias("i"), F.greatest("at", "other").alias("j"), "at", "rep", "n", "g", "c")
            dealt = dealt.repartition(tasks, "key", "i", "j").sortWithinPartitions("key", "i", "j")
            pairs = dealt.mapInArrow(H.tidy(_bounded(percent)), "a long, b long")
        pairs = pairs.distinct()
        pairs = store(pairs.join(tested, ["a", "b"], "left_anti"), "pairs")
        if pairs.isEmpty():
            continue
        more = store(confirmed(pairs), "links")
        tested = tested.unionByName(pairs)
        if not more.isEmpty():
            # groups found before stand for their members
            heads = lambda c: F.coalesce(F.col(f"c_{c}"), F.col(c))
            side = lambda c: final.select(F.col("rep").alias(c), F.col("component").alias(f"c_{c}"))
            joined = components(more.join(side("a"), "a", "left").join(side("b"), "b", "left").select(heads("a").alias("a"), heads("b").alias("b")))
            joined = joined.select("node", F.col("component").alias("to"))
            known = final.join(joined, F.col("component") == F.col("node"), "left").select("rep", F.coalesce("to", "component").alias("component"))
            new = joined.join(final, F.col("node") == F.col("rep"), "left_anti").select(F.col("node").alias("rep"), F.col("to").alias("component"))
            final = store(known.unionByName(new), "groups")

    named = reps.select("x", "y", "n", "rep", "head").join(final, "rep", "left").select("x", "y", "n", "head", F.coalesce("component", "rep").alias("component"))
    least = named.groupBy("component").agg(F.min("head").alias("least"))
    return signs.select("doc_id", "mark", "n", "x", "y"), named.join(least, "component").select("x", "y", "n", "head", "least")


def groups(docs: DataFrame, k: int = 5, percent: int = 80, bands: int = BANDS, width: int = ROWS) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of `docs`; rows without id have no component and are kept."""
    signs, sets = _grouped(docs, k, percent, bands, width)
    rows = signs.join(sets, ["x", "y", "n"], "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("least.doc_id", "doc_id"))
    return rows.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def one_of_each(docs: DataFrame, k: int = 5, percent: int = 80) -> DataFrame:
    """`docs` with one document of each group of near-duplicates; repeated rows count once, rows without id stay."""
    signs, sets = _grouped(docs, k, percent, BANDS, ROWS)
    signs = signs.where("doc_id is not null")
    winners = sets.where("head = least").select("head.doc_id", "head.mark").unionByName(signs.where("n = 0").select("doc_id", "mark").distinct())
    times = signs.groupBy("doc_id", "mark").agg(F.count(F.lit(1)).alias("m")).where("m > 1")
    winners = winners.join(times, ["doc_id", "mark"], "left").select("doc_id", "mark", F.col("m").isNotNull().alias("again"))
    rows = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("mark"))
    there = rows.join(winners, ["doc_id", "mark"])
    once = there.where("again").groupBy("doc_id", "mark").agg(F.any_value("row").alias("row"))
    return there.where("not again").select("row").unionByName(once.select("row")).unionByName(rows.where("doc_id is null").select("row")).select("row.*")


#: All pairs that share a shingle, and what each document reaches; for two-word shingles and 80 percent.
SQL = r"""
WITH RECURSIVE split AS (
  SELECT CAST(doc_id AS BIGINT) AS doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), shingled AS MATERIALIZED (
  SELECT doc_id, list_distinct(CASE WHEN len(w) < 2 THEN w ELSE list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]) END) AS s FROM split
), sized AS MATERIALIZED (SELECT doc_id, CAST(len(s) AS BIGINT) AS n FROM shingled
), every AS MATERIALIZED (SELECT doc_id, len(s) AS n, hash(unnest(s)) AS sh FROM shingled
), links AS MATERIALIZED (
  SELECT a.doc_id AS p, b.doc_id AS q FROM every a JOIN every b ON a.sh = b.sh AND a.doc_id < b.doc_id AND 100 * least(a.n, b.n) >= 80 * greatest(a.n, b.n)
  GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))
), sides AS MATERIALIZED (SELECT p, q FROM links UNION ALL SELECT q, p FROM links
), reach(doc_id, least_id) USING KEY (doc_id) AS (
  SELECT doc_id, doc_id FROM sized
  UNION
  SELECT c.doc_id, min(x.least_id) FROM reach x JOIN sides ON sides.p = x.doc_id JOIN recurring.reach c ON c.doc_id = sides.q WHERE x.least_id < c.least_id GROUP BY c.doc_id
)
SELECT s.doc_id, s.n AS n_shingles, r.least_id AS component_id, r.least_id = s.doc_id AS kept FROM sized s JOIN reach r USING (doc_id)
"""
