"""Vector corpora derived from the given tables by signed feature hashing.

A token's slot is the first seven hexadecimal digits of its MD5 modulo the
dimension, its sign the parity of the eighth; the sums are scaled to unit
length. Everything is integer arithmetic until the last step, so SQL gives the
same vectors. Rows without a token (or whose signs cancel) have no direction and
are left out. Rows that two columns name get 60 bits of a hash of both as their
id, and a table that tells which row it is (``line_ids``, ``turn_ids``).
"""

from __future__ import annotations

import hashlib
from itertools import islice

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, functions as F

from .session import ship
from .tables import load


#: Bytes of doubles that rows are added up in at once.
HASHED_BYTES = 8 << 20


def _slots(tokens, dim: int):
    """(slot, sign) of each token of an array column."""
    digest = lambda t: F.md5(t.cast("binary"))
    kept = F.filter(tokens, lambda t: t.isNotNull() & (t != ""))
    return (
        F.transform(kept, lambda t: (F.conv(F.substring(digest(t), 1, 7), 16, 10).cast("bigint") % dim).cast("int")),
        F.transform(kept, lambda t: (1 - 2 * (F.conv(F.substring(digest(t), 8, 1), 16, 10).cast("bigint") % 2)).cast("int")),
    )


def hash_rows(rows: DataFrame, dim: int) -> DataFrame:
    """(vec_id, embedding) of ``rows(vec_id, tokens array<string>)``: each row by itself, nothing is shuffled."""
    ship(rows.sparkSession)
    slots, signs = _slots(F.col("tokens"), dim)

    def work(batches):
        for whole in batches:
            step = max(1, HASHED_BYTES // (8 * dim))
            for i in range(0, whole.num_rows, step):
                b = whole.slice(i, step)
                out = np.zeros((b.num_rows, dim), dtype=np.float64)
                sizes = np.diff(b.column(1).offsets.to_numpy())
                np.add.at(out, (np.repeat(np.arange(b.num_rows), sizes), b.column(1).flatten().to_numpy()), b.column(2).flatten().to_numpy())
                norm = np.sqrt((out * out).sum(axis=1))
                kept = norm > 0
                out = out[kept] / norm[kept, None]
                yield _vectors(b.column(0).filter(pa.array(kept)), out, dim)

    full = rows.where("tokens is not null").select("vec_id", slots.alias("slots"), signs.alias("signs"))
    return full.mapInArrow(work, "vec_id bigint, embedding array<float>")


def _vectors(ids: pa.Array, x: np.ndarray, dim: int) -> pa.RecordBatch:
    ends = pa.array(np.arange(len(x) + 1, dtype=np.int32) * dim)
    return pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(ends, pa.array(x.astype(np.float32).ravel()))], ["vec_id", "embedding"])


def hash_vectors(tokens: DataFrame, dim: int) -> DataFrame:
    """(vec_id, embedding) of ``tokens(vec_id, token)``, whose tokens of an id stand in many rows: sparse sums first, then one array for each id."""
    digest = F.md5(F.col("token").cast("binary"))
    slots = tokens.where("token is not null and token != ''").select(
        "vec_id",
        (F.conv(F.substring(digest, 1, 7), 16, 10).cast("bigint") % dim).cast("int").alias("slot"),
        (1 - 2 * (F.conv(F.substring(digest, 8, 1), 16, 10).cast("bigint") % 2)).alias("sign"),
    )
    sums = slots.groupBy("vec_id", "slot").agg(F.sum("sign").alias("v")).where("v != 0")
    rows = sums.groupBy("vec_id").agg(F.collect_list("slot").alias("slots"), F.collect_list("v").alias("values"), F.sqrt(F.sum((F.col("v") * F.col("v")).cast("double"))).alias("norm"))
    return _dense(rows, dim)


def _dense(rows: DataFrame, dim: int) -> DataFrame:
    """(vec_id, embedding) of ``rows(vec_id, slots, values, norm)``: sparse sums scattered into arrays, batch by batch."""
    ship(rows.sparkSession)

    def work(batches):
        for b in batches:
            if not b.num_rows:
                continue
            out = np.zeros((b.num_rows, dim), dtype=np.float64)
            at = np.repeat(np.arange(b.num_rows), np.diff(b.column(1).offsets.to_numpy()))
            out[at, b.column(1).flatten().to_numpy()] = b.column(2).flatten().to_numpy()
            out /= b.column(3).to_numpy()[:, None]
            yield _vectors(b.column(0), out, dim)

    return rows.select("vec_id", "slots", "values", "norm").mapInArrow(work, "vec_id bigint, embedding array<float>")


def hash_vectors_sql(tokens: str, dim: int) -> str:
    """The same in DuckDB's SQL; ``tokens`` is a query with vec_id and token."""
    return f"""SELECT vec_id, list_transform(range(0, {dim}), lambda i: CAST(coalesce(map_extract(m, i)[1], 0) / norm AS FLOAT)) AS embedding FROM (
      SELECT vec_id, map_from_entries(list((slot, v))) AS m, sqrt(sum(CAST(v * v AS DOUBLE))) AS norm FROM (
        SELECT vec_id, CAST(('0x' || substr(md5(token), 1, 7))::BIGINT % {dim} AS BIGINT) AS slot,
          CAST(sum(1 - 2 * (('0x' || substr(md5(token), 8, 1))::BIGINT % 2)) AS BIGINT) AS v
        FROM ({tokens}) WHERE token IS NOT NULL AND token <> '' GROUP BY vec_id, slot) WHERE v <> 0 GROUP BY vec_id)"""


def _words(table: DataFrame, key: str, text: str) -> DataFrame:
    return table.select(F.col(key).alias("vec_id"), F.split(F.col(text), " ").alias("tokens"))


def hashed_id(*parts: str):
    """An id for rows that two or more columns name: 60 bits of the MD5 of both, the same in SQL."""
    whole = F.concat_ws("/", *[F.col(p).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(whole.cast("binary")), 1, 15), 16, 10).cast("bigint")


def hashed_id_sql(*parts: str) -> str:
    return f"CAST(('0x' || substr(md5({' || chr(47) || '.join(f'CAST({p} AS VARCHAR)' for p in parts)}), 1, 15)) AS BIGINT)"


def doc_vec(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    return hash_rows(_words(load(spark, sf_dir, "documents"), "doc_id", "text"), dim)


DOC_TOKENS_SQL = "SELECT doc_id AS vec_id, unnest(string_split(text, ' ')) AS token FROM documents"


def bench_vec(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    return hash_rows(_words(load(spark, sf_dir, "benchmark"), "item_id", "text"), dim)


BENCH_TOKENS_SQL = "SELECT item_id AS vec_id, unnest(string_split(text, ' ')) AS token FROM benchmark"


def page_vec(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    return hash_rows(_words(load(spark, sf_dir, "pages"), "page_id", "html"), dim)


PAGE_TOKENS_SQL = "SELECT page_id AS vec_id, unnest(string_split(html, ' ')) AS token FROM pages"


def turn_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, conv_id, turn, role, text) of every turn."""
    return load(spark, sf_dir, "conversations").select(hashed_id("conv_id", "turn").alias("vec_id"), "conv_id", "turn", "role", "text")


def conv_vec(spark: SparkSession, sf_dir: str, dim: int, role: str | None = None) -> DataFrame:
    rows = turn_ids(spark, sf_dir)
    return hash_rows(_words(rows if role is None else rows.where(F.col("role") == role), "vec_id", "text"), dim)


CONV_TOKENS_SQL = f"SELECT {hashed_id_sql('conv_id', 'turn')} AS vec_id, unnest(string_split(text, ' ')) AS token FROM conversations"


def line_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, doc_id, n, line) of every line of every document; n counts from 0."""
    lines = load(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("n", "line"))
    return lines.select(hashed_id("doc_id", "n").alias("vec_id"), "doc_id", "n", "line")


def doc_line_vec(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    """All lines of documents that have a word."""
    return hash_rows(_words(line_ids(spark, sf_dir), "vec_id", "line"), dim)


LINE_TOKENS_SQL = f"SELECT {hashed_id_sql('doc_id', 'n - 1')} AS vec_id, unnest(string_split(line, ' ')) AS token FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS n FROM documents)"


def word_vec(spark: SparkSession, sf_dir: str, dim: int, least: int = 10) -> DataFrame:
    """Words by the words within two places of them; a word belongs to the vocabulary if it occurs ``least`` times.

    A task hashes a word once and adds up what it meets; only a row for each word
    and task is shuffled, so very common words are not many rows either.
    """
    ship(spark)

    def work(batches):
        for b in batches:
            yield from _word_vectors(b, dim, least, carried)
        yield from _word_vectors(None, dim, least, carried)

    carried: list[pa.RecordBatch] = []
    met = word_sums(load(spark, sf_dir, "documents").select("text"), dim).repartition("word").sortWithinPartitions("word")
    return met.mapInArrow(work, "word string, embedding array<float>").select(hashed_id("word").alias("vec_id"), "embedding")


#: Bytes of text whose words are taken at once; (word, slot) sums and words that a task holds before it gives them out.
WORD_BYTES, WORD_SUMS, WORDS_HELD = 4 << 20, 4_000_000, 500_000


def word_sums(texts: DataFrame, dim: int) -> DataFrame:
    """(word, n, slots, signs) of ``texts(text)``: how often a task met a word, and the sums of its neighbours' signs by slot, as int32 arrays."""
    ship(texts.sparkSession)

    def work(batches):
        held = _Words(dim)
        for b in batches:
            column = b.column(0)
            ends = np.cumsum(pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64))
            i = 0
            while i < len(column):
                j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + WORD_BYTES, side="right")))
                held.add(column.slice(i, j - i))
                i = j
                if held.full():
                    yield held.out()
                    held = _Words(dim)
        yield held.out()

    return texts.mapInArrow(work, "word string, n bigint, slots binary, signs binary")


class _Words:
    """Words that a task has met: each hashed once, its neighbours' signs added up by slot."""

    def __init__(self, dim: int):
        self.dim, self.number, self.sums, self.merged = dim, {}, [], 0
        self.slot, self.sign, self.n = (np.zeros(0, dtype=np.int64) for _ in range(3))

    def add(self, texts: pa.Array) -> None:
        lists = pc.split_pattern(texts.drop_null(), " ")
        coded = lists.flatten().dictionary_encode()
        if not len(coded):
            return
        words, number = coded.dictionary.to_pylist(), self.number
        known = len(number)
        place = np.array([number.setdefault(w, len(number)) for w in words], dtype=np.int64)
        new = [hashlib.md5(w.encode()).hexdigest() for w in list(islice(number, known, None))]
        self.slot = np.append(self.slot, [int(h[:7], 16) % self.dim for h in new]).astype(np.int64)
        self.sign = np.append(self.sign, [1 - 2 * (int(h[7], 16) % 2) for h in new]).astype(np.int64)
        self.n = np.append(self.n, np.zeros(len(new), dtype=np.int64))
        there = place != number.get("", -1)  # empty words keep their place between others, no more
        met = coded.indices.to_numpy(zero_copy_only=False)
        self.n += np.bincount(place, weights=np.bincount(met, minlength=len(words)), minlength=len(number)).astype(np.int64)
        at, full = place[met], there[met]
        text = np.repeat(np.arange(len(lists)), pc.list_value_length(lists).to_numpy(zero_copy_only=False))
        keys, signs = [], []
        for step in (1, 2):
            both = (text[:-step] == text[step:]) & full[:-step] & full[step:]
            a, b = at[:-step][both], at[step:][both]
            keys += [a * self.dim + self.slot[b], b * self.dim + self.slot[a]]
            signs += [self.sign[b], self.sign[a]]
        self.sums.append(_added(np.concatenate(keys), np.concatenate(signs)))
        if sum(len(k) for k, _ in self.sums) > self.merged + WORD_SUMS:
            self._merge()

    def _merge(self) -> None:
        if self.sums:
            self.sums = [_added(*(np.concatenate([s[j] for s in self.sums]) for j in (0, 1)))]
            self.merged = len(self.sums[0][0])

    def full(self) -> bool:
        return self.merged > WORD_SUMS or len(self.number) > WORDS_HELD

    def out(self) -> pa.RecordBatch:
        """The rows of all words met."""
        self._merge()
        keys, signs = self.sums[0] if self.sums else (np.zeros(0, dtype=np.int64),) * 2
        ends = np.searchsorted(keys, np.arange(len(self.number) + 1) * self.dim).astype(np.int32) * 4
        blob = lambda v: pa.Array.from_buffers(pa.binary(), len(self.number), [None, pa.py_buffer(ends), pa.py_buffer(v.astype(np.int32))])
        rows = pa.RecordBatch.from_arrays([pa.array(list(self.number), type=pa.string()), pa.array(self.n), blob(keys % self.dim), blob(signs)], ["word", "n", "slots", "signs"])
        return rows.filter(pc.not_equal(rows.column(0), ""))


def _added(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct keys in order and the sum of the values of each."""
    if not len(keys):
        return keys, values
    order = np.argsort(keys)
    keys, values = keys[order], values[order]
    begins = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    return keys[begins], np.add.reduceat(values, begins)


def _word_vectors(batch: pa.RecordBatch | None, dim: int, least: int, carried: list[pa.RecordBatch]):
    """(word, embedding) of rows in order of their words; the rows of the last word wait in ``carried``, as the next batch may have more of it."""
    parts = carried + ([batch] if batch is not None and batch.num_rows else [])
    carried.clear()
    if not parts:
        return
    rows = pa.Table.from_batches(parts).combine_chunks()
    words = rows.column("word").combine_chunks().to_pylist()
    begins = [i for i, w in enumerate(words) if i == 0 or w != words[i - 1]]
    if batch is not None:
        carried += rows.slice(begins[-1]).to_batches()
        rows, begins = rows.slice(0, begins[-1]), begins[:-1]
    begins.append(rows.num_rows)
    step = max(1, (64 << 20) // (8 * dim))
    for i in range(0, len(begins) - 1, step):
        some = begins[i : i + step + 1]
        part = rows.slice(some[0], some[-1] - some[0])
        own = np.repeat(np.arange(len(some) - 1), np.diff(some))
        n = np.bincount(own, weights=part.column("n").to_numpy(), minlength=len(some) - 1)
        slots, signs = (part.column(c).to_pylist() for c in ("slots", "signs"))
        own = np.repeat(own, [len(v) // 4 for v in slots])
        out = np.zeros((len(some) - 1, dim), dtype=np.float64)
        np.add.at(out, (own, np.frombuffer(b"".join(slots), dtype=np.int32)), np.frombuffer(b"".join(signs), dtype=np.int32))
        norm = np.sqrt((out * out).sum(axis=1))
        kept = (n >= least) & (norm > 0)
        named = pa.array([words[b] for b, k in zip(some, kept) if k], type=pa.string())
        vectors = _vectors(named, out[kept] / norm[kept, None], dim)
        yield pa.RecordBatch.from_arrays(vectors.columns, ["word", "embedding"])


def line_vec(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    """Rows of lineitem by their values: each column with its band is a token. An order repeats line numbers, so part, supplier and day belong to the id."""
    band = lambda name, c: F.concat(F.lit(f"{name}="), c.cast("string"))
    tokens = F.array(
        band("part", (F.col("l_partkey") % 97)),
        band("supplier", (F.col("l_suppkey") % 53)),
        band("quantity", F.col("l_quantity").cast("int")),
        band("price", (F.col("l_extendedprice") / 2000).cast("int")),
        band("discount", F.round(F.col("l_discount") * 100).cast("int")),
        band("tax", F.round(F.col("l_tax") * 100).cast("int")),
        band("flag", F.concat("l_returnflag", "l_linestatus")),
        F.concat(F.lit("month="), F.date_format("l_shipdate", "yyyy-MM")),
        F.concat(F.lit("day="), F.date_format("l_shipdate", "dd")),
    )
    return hash_rows(load(spark, sf_dir, "lineitem").select(hashed_id("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate").alias("vec_id"), tokens.alias("tokens")), dim)


LINEITEM_TOKENS_SQL = f"""SELECT {hashed_id_sql('l_orderkey', 'l_linenumber', 'l_partkey', 'l_suppkey', 'l_shipdate')} AS vec_id, unnest(['part=' || l_partkey % 97, 'supplier=' || l_suppkey % 53, 'quantity=' || CAST(trunc(l_quantity) AS INTEGER),
  'price=' || CAST(trunc(l_extendedprice / 2000) AS INTEGER), 'discount=' || CAST(round(l_discount * 100) AS INTEGER), 'tax=' || CAST(round(l_tax * 100) AS INTEGER), 'flag=' || l_returnflag || l_linestatus,
  'month=' || strftime(l_shipdate, '%Y-%m'), 'day=' || strftime(l_shipdate, '%d')]) AS token FROM lineitem"""


def part_vec(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    rows = load(spark, sf_dir, "part")
    tokens = F.concat(
        F.split("p_name", " "),
        F.split("p_type", " "),
        F.array(F.concat(F.lit("brand="), "p_brand"), F.concat(F.lit("size="), F.col("p_size").cast("string")), F.concat(F.lit("price="), (F.col("p_retailprice") / 50).cast("int").cast("string"))),
    )
    return hash_rows(rows.select(F.col("p_partkey").alias("vec_id"), tokens.alias("tokens")), dim)


PART_TOKENS_SQL = """SELECT p_partkey AS vec_id, unnest(list_concat(string_split(p_name, ' '), string_split(p_type, ' '),
  ['brand=' || p_brand, 'size=' || p_size, 'price=' || CAST(trunc(p_retailprice / 50) AS INTEGER)])) AS token FROM part"""


def user_vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users by counts of (hour, event type): 24 x 5 numbers, unit length; the five kinds of events are fixed."""
    kinds = ["click", "error", "purchase", "signup", "view"]
    rows = load(spark, sf_dir, "events").select("user_id", F.hour("ts").alias("h"), "event_type")
    found = rows.where(F.col("event_type").isin(kinds)).groupBy("user_id", "h", "event_type").count()
    slot = F.col("h") * 5 + F.array_position(F.array(*[F.lit(k) for k in kinds]), F.col("event_type")).cast("int") - 1
    sums = found.groupBy("user_id", slot.alias("slot")).agg(F.sum("count").alias("v"))
    rows = sums.groupBy(F.col("user_id").alias("vec_id")).agg(F.collect_list("slot").alias("slots"), F.collect_list("v").alias("values"), F.sqrt(F.sum((F.col("v") * F.col("v")).cast("double"))).alias("norm"))
    return _dense(rows, 24 * len(kinds))


USER_VEC_SQL = """SELECT user_id AS vec_id, list_transform(range(0, 120), lambda i: CAST(coalesce(map_extract(m, i)[1], 0) / norm AS FLOAT)) AS embedding FROM (
  SELECT user_id, map_from_entries(list((slot, v))) AS m, sqrt(sum(CAST(v * v AS DOUBLE))) AS norm FROM (
    SELECT user_id, CAST(hour(ts) * 5 + list_position(['click','error','purchase','signup','view'], event_type) - 1 AS BIGINT) AS slot, count(*) AS v
    FROM events WHERE event_type IN ('click','error','purchase','signup','view') GROUP BY 1, 2) GROUP BY user_id)"""


def customer_vec(spark: SparkSession, sf_dir: str, dim: int) -> DataFrame:
    """Customers by tokens of their orders: month, priority, status and price band."""
    orders = load(spark, sf_dir, "orders")
    tokens = F.array(
        F.concat(F.lit("month="), F.date_format("o_orderdate", "yyyy-MM")),
        F.concat(F.lit("priority="), "o_orderpriority"),
        F.concat(F.lit("status="), "o_orderstatus"),
        F.concat(F.lit("price="), (F.col("o_totalprice") / 20_000).cast("int").cast("string")),
    )
    return hash_vectors(orders.select(F.col("o_custkey").alias("vec_id"), F.explode(tokens).alias("token")), dim)


CUSTOMER_TOKENS_SQL = """SELECT o_custkey AS vec_id, unnest(['month=' || strftime(o_orderdate, '%Y-%m'), 'priority=' || o_orderpriority, 'status=' || o_orderstatus,
  'price=' || CAST(trunc(o_totalprice / 20000) AS INTEGER)]) AS token FROM orders"""


def embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "embeddings").select("vec_id", "embedding")


def valid(df: DataFrame, dim: int, vector: str = "embedding") -> DataFrame:
    """Rows whose vector has the right length and finite numbers only."""
    bad = F.exists(vector, lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
    return df.where((F.size(vector) == dim) & ~bad)


def held_out(df: DataFrame, n: int) -> tuple[DataFrame, DataFrame]:
    """(corpus, queries): the n ids with the least MD5 become queries and leave the corpus."""
    chosen = df.select("vec_id").orderBy(F.md5(F.col("vec_id").cast("string").cast("binary"))).limit(n)
    queries = df.join(F.broadcast(chosen), "vec_id").select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))
    return df.join(F.broadcast(chosen), "vec_id", "left_anti"), queries


def native_queries(df: DataFrame) -> DataFrame:
    """The query set of searches within a corpus: every id divisible by 100."""
    return df.where("vec_id % 100 = 0").select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))
