"""Set-similarity self-join of texts on five-word shingles by chosen paths.

A text is the set of its shingles. In every run a set enters the buckets of a few shingles
that a shared hash samples from it, with about ``1 / threshold`` expected choices. Buckets of up to
``bucket_limit`` sets are compared set by set on short sketches. The sets of larger ones are sampled
again, in more runs, down to ``levels`` choices, as a deeper path is shared less often, and then compared in tiles. The numbers
of runs and the sketches' margin follow from ``target_recall``: a pair at the threshold, however large its buckets,
shares no compared bucket or fails its sketches with at most a chance of ``1 - target_recall``. Sets
whose sketches agree form clusters, and within a cluster every pair is compared exactly on
its whole shingle sets, so links are never estimated.

Texts with the same words are one class from the start: they are counted, not compared. A text
is known by the 128-bit digest of its words and the row that stands for it, never by a document's id,
so one id may have several texts. Large buckets and clusters are split into pairs of tiles. Nothing
emits a row for each pair: a tile returns a spanning forest and the number of links of each member.

Defined results: a document with null id, or without a word, links with nothing and is its
own class; texts of one to four words have one shingle, all their words; repeated rows
are copies; rows of one id with different texts are documents of their own, and links between them
count; of the rows of a class that share its smallest id one stays; an empty table gives an empty
table. Other columns pass through :func:`without_near_duplicates` and are ignored by the others.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphparts.llm.common import dropped, mapped, mix, odd_constants, utf8, word_hashes, written
from graphparts.operators.components import connected_components
from graphparts.plans.skew import hub_limit, join_per_key

SLOTS = 64
#: The most texts that a Python worker takes apart at once.
TEXTS = 512
LEVELS = 2
_ROW, _D1, _D2, _N, _FIRST, _SKETCH = "_nj_row", "_nj_d1", "_nj_d2", "_nj_n", "_nj_p1", "_nj_sketch"
_OWN = f"{_D1} bigint, {_D2} bigint, {_N} int, {_FIRST} array<bigint>, {_SKETCH} binary"


def shared_path(level: int) -> float:
    """The least chance of a pair at the threshold to share a path of ``level`` choices in one run: one shared choice is expected at each."""
    chance = 1.0
    for _ in range(level):
        chance = 1 - math.exp(-chance)
    return chance


def runs_for(target_recall: float, level: int) -> int:
    """Runs until a pair at the threshold misses all paths of ``level`` choices with a third of the allowed chance; the others are the first level's, for hot pairs, and the sketches'."""
    if not 0 < target_recall < 1:
        raise ValueError("target_recall must lie between 0 and 1")
    return math.ceil(math.log((1 - target_recall) / 3) / math.log(1 - shared_path(level)))


def least_agreement(target_recall: float, threshold: float) -> int:
    """The most equal slots that a pair at the threshold falls below with a third of the allowed chance."""
    below, k = 0.0, 0
    while k < SLOTS:
        below += math.comb(SLOTS, k) * threshold**k * (1 - threshold) ** (SLOTS - k)
        if below > (1 - target_recall) / 3:
            break
        k += 1
    return k


def shingles(words: list[bytes], size: int = 5) -> np.ndarray:
    """Sorted distinct hashes of the runs of ``size`` words; fewer words are one run."""
    if not words:
        return np.zeros(0, np.uint64)
    h = word_hashes(words)
    size = min(size, len(words))
    n = len(h) - size + 1
    total = np.full(n, np.uint64(size), np.uint64)
    for j, c in enumerate(odd_constants(size, 11)):
        total += h[j : j + n] * c
    return np.unique(mix(total))


def _chosen(tokens: np.ndarray, node: np.uint64, limit: np.uint64) -> np.ndarray:
    """Keys of the children of ``node`` that this set enters."""
    draw = mix(tokens ^ node)
    hit = draw < limit
    return mix(draw[hit] ^ np.array([node]) * np.uint64(3))


def _limit(tokens: np.ndarray, threshold: float) -> np.uint64:
    rate = min(1.0, 1.0 / (threshold * len(tokens)))
    return np.uint64(min(2**64 - 1, int(rate * 2**64)))


def first_choices(tokens: np.ndarray, runs: int, threshold: float) -> np.ndarray:
    limit = _limit(tokens, threshold)
    return np.unique(np.concatenate([_chosen(tokens, root, limit) for root in odd_constants(runs, 12)]))


def paths(tokens: np.ndarray, runs: int, threshold: float, levels: int) -> tuple[list, list]:
    """Keys of the first level, and for each further one its keys with their parents."""
    limit = _limit(tokens, threshold)
    one = first_choices(tokens, runs, threshold)
    level, deeper = one, []
    for _ in range(levels - 1):
        found = [(p, c) for p in level for c in np.unique(_chosen(tokens, p, limit))]
        deeper.append([{"parent": p, "key": k} for p, k in np.array(found, np.uint64).reshape(-1, 2).view(np.int64).tolist()])
        level = np.unique(np.array([c for _, c in found], np.uint64))
    return one.view(np.int64).tolist(), deeper


def sketch_of(tokens: np.ndarray) -> bytes:
    """The low byte of each of 64 minima."""
    c = odd_constants(SLOTS, 13)
    least = (tokens[None, :] * c[:, None]).min(axis=1)
    return mix(least).astype(np.uint8).tobytes()


def _digest(words: list[bytes]) -> list[int]:
    import xxhash

    return np.frombuffer(xxhash.xxh3_128_digest(b" ".join(words)), np.int64).tolist()


def _shingled(docs: DataFrame, doc_id: str, text: str, runs: int, threshold: float, size: int) -> DataFrame:
    """``docs`` written with a number, the digest, sketch and first choices of every row; nulls where there is nothing to compare."""
    names = [c for c in docs.columns if not c.startswith("_nj_")]
    plain = docs.select(*(F.col(f"`{c}`") for c in names))
    at_id, at_text = names.index(doc_id), names.index(text)

    def run(batch: pa.RecordBatch) -> dict:
        out: dict = {k: [] for k in (_D1, _D2, _N, _FIRST, _SKETCH)}
        for i, t in zip(batch.column(at_id).to_pylist(), batch.column(at_text).to_pylist(), strict=True):
            words = utf8(t).split()
            if i is None or not words:
                row = (None, None, 0, [], None)
            else:
                tokens = shingles(words, size)
                row = (*_digest(words), len(tokens), first_choices(tokens, runs, threshold).view(np.int64).tolist(), sketch_of(tokens))
            for k, v in zip(out, row, strict=True):
                out[k].append(v)
        return dict(zip(names, batch.columns, strict=True)) | out

    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in plain.schema), _OWN])
    # Numbers drawn while writing are fixed from then on.
    return written(mapped(plain, run, schema, TEXTS).withColumn(_ROW, F.monotonically_increasing_id()), "shingled")


def _deepened(runs: int, threshold: float, size: int, levels: int) -> Callable[[pa.RecordBatch], dict]:
    def run(batch: pa.RecordBatch) -> dict:
        found = [paths(shingles(utf8(t).split(), size), runs, threshold, levels) for t in batch.column(1).to_pylist()]
        return {"rep": batch.column(0).to_pylist(), "p1": [x[0] for x in found]} | {f"p{k + 2}": [x[1][k] for x in found] for k in range(levels - 1)}

    return run


def _groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """Runs of rows with equal ``keys``, whole, from batches sorted by them."""
    held: list[pa.RecordBatch] = []

    def cut(table: pa.Table, last: bool) -> tuple[list[tuple[int, int]], int]:
        change = np.zeros(max(0, table.num_rows - 1), bool)
        for k in keys:
            x = table.column(k).combine_chunks().to_numpy(zero_copy_only=False)
            change |= x[1:] != x[:-1]
        ends = [*(np.flatnonzero(change) + 1).tolist(), *([table.num_rows] if last else [])]
        return list(zip([0, *ends], ends, strict=False)), ends[-1] if ends else 0

    for batch in batches:
        if not batch.num_rows:
            continue
        if held and all(batch.column(batch.schema.get_field_index(k))[-1] == held[0].column(held[0].schema.get_field_index(k))[0] for k in keys):
            held.append(batch)
            continue
        table = pa.Table.from_batches([*held, batch])
        spans, rest = cut(table, False)
        for a, b in spans:
            yield table.slice(a, b - a)
        held = table.slice(rest).to_batches()
    if held:
        table = pa.Table.from_batches(held)
        for a, b in cut(table, True)[0]:
            yield table.slice(a, b - a)


def _forest(left: np.ndarray, right: np.ndarray, n: int) -> list[tuple[int, int]]:
    """Edges of a spanning forest of the graph on 0..n-1 with the given pairs."""
    parent = list(range(n))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    out = []
    for a, b in zip(left.tolist(), right.tolist(), strict=True):
        ra, rb = root(a), root(b)
        if ra != rb:
            parent[max(ra, rb)] = min(ra, rb)
            out.append((a, b))
            if len(out) == n - 1:
                break
    return out


def _tiled(rows: DataFrame, key: str, member: str, count: str, tile: int | Column) -> DataFrame:
    """Rows of groups with more than ``tile`` members, copied to the pairs of tiles they belong to."""
    g = F.ceil(F.col(count) / F.lit(tile)).cast("int")
    own = F.pmod(F.xxhash64(F.lit(5), member), g).cast("int")
    dealt = rows.withColumn("_g", g).withColumn("_own", own).withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_g") - 1)))
    return dealt.withColumn("_a", F.least("_own", "_other")).withColumn("_b", F.greatest("_own", "_other")).drop("_g", "_other")


def _in_groups(rows: DataFrame, key: str, function: Callable[[pa.Table], list[dict]], schema: str) -> DataFrame:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    arrow = to_arrow_schema(StructType.fromDDL(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ready: list[dict] = []
        for group in _groups(batches, [key, "_a", "_b"]):
            ready += function(group)
            if len(ready) >= 5000:
                yield pa.RecordBatch.from_pylist(ready, schema=arrow)
                ready = []
        if ready:
            yield pa.RecordBatch.from_pylist(ready, schema=arrow)

    return rows.repartition(key, "_a", "_b").sortWithinPartitions(key, "_a", "_b").mapInArrow(run, schema)


def _sides(group: pa.Table) -> tuple[np.ndarray, np.ndarray, bool]:
    """Places of the left and the right tile's rows, and whether they are one tile."""
    a, b = group.column("_a")[0].as_py(), group.column("_b")[0].as_py()
    if a == b:
        every = np.arange(group.num_rows)
        return every, every, True
    own = group.column("_own").to_numpy()
    return np.flatnonzero(own == a), np.flatnonzero(own == b), False


def _similar_sketches(threshold: float, least: int) -> Callable[[pa.Table], list[dict]]:
    def run(group: pa.Table) -> list[dict]:
        left, right, same = _sides(group)
        if len(left) == 0 or len(right) == 0 or (same and len(left) < 2):
            return []
        v = group.column("rep").to_numpy()
        n = group.column("n").to_numpy().astype(float)
        s = np.frombuffer(b"".join(group.column("sketch").to_pylist()), np.uint8).reshape(-1, SLOTS)
        found_a, found_b = [], []
        for begin in range(0, len(left), 128):
            part = left[begin : begin + 128]
            agree = np.zeros((len(part), len(right)), np.uint8)
            for slot in range(SLOTS):
                agree += s[part, slot][:, None] == s[right, slot][None, :]
            ok = (agree >= least) & (np.minimum(n[part][:, None], n[right][None, :]) >= threshold * np.maximum(n[part][:, None], n[right][None, :]))
            if same:
                ok &= part[:, None] < right[None, :]
            i, j = np.nonzero(ok)
            found_a.append(part[i])
            found_b.append(right[j])
        return [{"src": int(v[i]), "dst": int(v[j])} for i, j in _forest(np.concatenate(found_a), np.concatenate(found_b), len(v))]

    return run


def _exact(threshold: float, size: int) -> Callable[[pa.Table], list[dict]]:
    """Links of a pair of tiles: for each member its linked documents and texts, and a spanning forest."""

    def run(group: pa.Table) -> list[dict]:
        v, copies = group.column("rep").to_numpy(), group.column("copies").to_numpy()
        left, right, same = _sides(group)
        if len(left) == 0 or len(right) == 0 or (same and len(left) < 2):
            return []
        sets = [shingles(utf8(t).split(), size) for t in group.column("text").to_pylist()]
        n = np.array([len(x) for x in sets])
        place = np.repeat(np.arange(len(sets)), n)
        _, token, often = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        shared = often[token] > 1
        place, token = place[shared], token[shared]
        _, token = np.unique(token, return_inverse=True)
        wide = int(token.max()) + 1 if len(token) else 0
        common = np.zeros((len(left), len(right)), np.float32)
        order = np.argsort(token, kind="stable")
        place, token = place[order], token[order]
        for begin in range(0, wide, 4096):
            a, b = np.searchsorted(token, [begin, begin + 4096])
            m = np.zeros((len(sets), min(4096, wide - begin)), np.float32)
            m[place[a:b], token[a:b] - begin] = 1
            common += m[left] @ m[right].T
        union = n[left][:, None] + n[right][None, :] - common
        linked = common >= threshold * union - 1e-9
        if same:
            np.fill_diagonal(linked, False)
        documents, texts = np.zeros(len(v), np.int64), np.zeros(len(v), np.int64)
        documents[left] += linked @ copies[right]
        texts[left] += linked.sum(axis=1)
        if not same:
            documents[right] += linked.T @ copies[left]
            texts[right] += linked.sum(axis=0)
        i, j = np.nonzero(linked)
        forest = _forest(left[i], right[j], len(v))
        out = [{"src": int(v[a]), "dst": int(v[b]), "documents": 0, "texts": 0} for a, b in forest]
        return out + [{"src": int(v[k]), "dst": None, "documents": int(documents[k]), "texts": int(texts[k])} for k in np.flatnonzero(texts)]

    return run


def _buckets(reps: DataFrame, texts: DataFrame, target_recall: float, threshold: float, size: int, bucket_limit: int, levels: int) -> DataFrame:
    """``(rep, key, c)``: the sets of every bucket that is compared, and how many they are."""

    def shared(rows: DataFrame, level: str) -> DataFrame:
        counts = written(rows.groupBy("key").agg(F.count("*").alias("c")).where("c > 1").withColumn("n", F.col("c")), f"{level}-counts")
        total = counts.agg(F.sum("c")).first()[0] or 0
        found = written(join_per_key(rows, counts, "key", "n", hub_limit(total)), level)
        dropped(counts.sparkSession, counts)
        return found

    first = shared(reps.select("rep", F.explode("p1").alias("key")), "level0")
    buckets = first.where(F.col("c") <= bucket_limit)
    large = first.where(F.col("c") > bucket_limit).select("rep").distinct()
    if not large.take(1):
        return buckets
    # A pair that shares a large bucket has both its sets here: only they need more runs.
    pair = "array<struct<parent:bigint,key:bigint>>"
    schema = ", ".join(["rep bigint", "p1 array<bigint>", *(f"p{k} {pair}" for k in range(2, levels + 1))])
    deep = written(mapped(large.join(texts, "rep"), _deepened(runs_for(target_recall, levels), threshold, size, levels), schema, TEXTS), "deep")
    rows = deep.select("rep", F.explode("p1").alias("key"))
    for level in range(1, levels + 1):
        found = shared(rows, f"level{level}")
        buckets = buckets.unionByName(found if level == levels else found.where(F.col("c") <= bucket_limit))
        if level == levels:
            break
        # Only the choices made below a large bucket go on; a set is in a bounded number of them.
        hot = found.where(F.col("c") > bucket_limit).groupBy("rep").agg(F.collect_list("key").alias("parents"))
        below = F.filter(f"p{level + 1}", lambda x: F.array_contains("parents", x["parent"]))
        rows = deep.join(hot, "rep").select("rep", F.explode(F.array_distinct(F.transform(below, lambda x: x["key"]))).alias("key"))
    return buckets


def _classes(every: DataFrame, doc_id: str, text: str, threshold: float, size: int, target_recall: float, bucket_limit: int, tile: int, levels: int) -> DataFrame:
    """``(d1, d2, text_id, class_id, class_row, n_links, n_texts)`` of every distinct text."""
    first = F.struct(F.col(doc_id).alias("doc_id"), F.col(_ROW).alias("row"))
    reps = written(
        every.where(F.col(_N) > 0)
        .groupBy(F.col(_D1).alias("d1"), F.col(_D2).alias("d2"))
        .agg(F.min(_ROW).alias("rep"), F.min(first).alias("first"), F.count("*").alias("copies"), F.min_by(F.struct(F.col(_N).alias("n"), F.col(_FIRST).alias("p1"), F.col(_SKETCH).alias("sketch")), _ROW).alias("x"))
        .select("rep", "first", "copies", "d1", "d2", "x.*"),
        "texts",
    )
    texts = every.where(F.col(_N) > 0).select(F.col(_ROW).alias("rep"), F.col(text).alias("text"))
    buckets = _buckets(reps, texts, target_recall, threshold, size, bucket_limit, levels)
    sketched = _tiled(buckets.join(reps.select("rep", "n", "sketch"), "rep"), "key", "rep", "c", tile)
    alike = _in_groups(sketched, "key", _similar_sketches(threshold, least_agreement(target_recall, threshold)), "src bigint, dst bigint").distinct()
    clusters = written(connected_components(alike).withColumnsRenamed({"v": "rep", "component": "cluster"}), "clusters")
    sizes = clusters.groupBy("cluster").agg(F.count("*").alias("c"))
    members = clusters.join(sizes, "cluster").join(reps.select("rep", "copies"), "rep").join(texts, "rep")
    found = written(_in_groups(_tiled(members, "cluster", "rep", "c", tile), "cluster", _exact(threshold, size), "src bigint, dst bigint, documents bigint, texts bigint"), "links")

    joined = connected_components(found.where("dst is not null")).withColumnsRenamed({"v": "rep", "component": "class"})
    links = found.where("dst is null").groupBy(F.col("src").alias("rep")).agg(F.sum("documents").alias("documents"), F.sum("texts").alias("texts"))
    of_class = joined.join(reps.select("rep", "first"), "rep").groupBy("class").agg(F.min("first").alias("lowest"))
    linked = joined.join(of_class, "class").select("rep", "lowest").join(links, "rep", "left")
    least = F.coalesce("lowest", "first")
    return reps.join(linked, "rep", "left").select(
        "d1", "d2", F.col("first.doc_id").alias("text_id"), least["doc_id"].alias("class_id"), least["row"].alias("class_row"),
        (F.coalesce("documents", F.lit(0)) + F.col("copies") - 1).cast("bigint").alias("n_links"),
        F.coalesce("texts", F.lit(0)).cast("bigint").alias("n_texts"),
    )


def _judged(docs: DataFrame, doc_id: str, text: str, threshold: float, size: int, target_recall: float, bucket_limit: int, tile: int, levels: int) -> tuple[DataFrame, DataFrame]:
    """The written rows, and for each ``(row, doc_id, text_id, class_id, class_row, n_links, n_texts)``."""
    every = _shingled(docs, doc_id, text, runs_for(target_recall, 1), threshold, size)
    classes = _classes(every, doc_id, text, threshold, size, target_recall, bucket_limit, tile, levels)
    rows = every.select(F.col(_ROW).alias("row"), F.col(doc_id).alias("doc_id"), F.col(_D1).alias("d1"), F.col(_D2).alias("d2"))
    return every, rows.join(classes, ["d1", "d2"], "left").drop("d1", "d2")


def near_duplicates(
    docs: DataFrame,
    *,
    doc_id: str = "doc_id",
    text: str = "text",
    threshold: float = 0.8,
    size: int = 5,
    target_recall: float = 0.9998,
    bucket_limit: int = 2000,
    tile: int = 1000,
    levels: int = LEVELS,
) -> DataFrame:
    """One row per document: ``doc_id, text_id, class_id, n_links, n_texts, kept``.

    ``text_id`` is the smallest id of the documents with the same words, ``class_id`` the
    smallest id reachable over links of similarity ``threshold`` or more, ``n_links`` the number of
    other documents linked directly (copies included), ``n_texts`` the number of other
    texts among them, and ``kept`` marks the one document of its class that stays.
    """
    plain = docs.select(F.col(doc_id).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text"))
    _, rows = _judged(plain, "doc_id", "text", threshold, size, target_recall, bucket_limit, tile, levels)
    none = F.lit(0).cast("bigint")
    return rows.select(
        "doc_id",
        F.coalesce("text_id", "doc_id").alias("text_id"),
        F.coalesce("class_id", "doc_id").alias("class_id"),
        F.coalesce("n_links", none).alias("n_links"),
        F.coalesce("n_texts", none).alias("n_texts"),
        F.coalesce(F.col("row") == F.col("class_row"), F.lit(True)).alias("kept"),
    )


def without_near_duplicates(
    docs: DataFrame,
    *,
    doc_id: str = "doc_id",
    text: str = "text",
    threshold: float = 0.8,
    size: int = 5,
    target_recall: float = 0.9998,
    bucket_limit: int = 2000,
    tile: int = 1000,
    levels: int = LEVELS,
) -> DataFrame:
    """The rows of ``docs``, one of each class: rows are dropped, not ids, so no text goes that has not a near copy left."""
    every, rows = _judged(docs, doc_id, text, threshold, size, target_recall, bucket_limit, tile, levels)
    gone = rows.where(F.col("row") != F.col("class_row")).select(F.col("row").alias(_ROW))
    return every.join(gone, _ROW, "left_anti").select(*(F.col(f"`{c}`") for c in docs.columns))
