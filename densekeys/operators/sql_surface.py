"""Functions as SQL: lookups and membership over broadcast artifacts, fingerprints, parities, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from densekeys.functions.encode import encoded_string
from densekeys.functions.kernel import peel
from densekeys.operators.filters import SlotFilter, signature_of
from densekeys.plans.build import Artifact, functions_of
from densekeys.plans.evaluate import BROADCAST_BYTES, _answers, stored_bytes
from densekeys.plans.fingerprints import as_longs, word_count, words_of
from densekeys.plans.params import Params


def _named(function, *kinds):
    """Annotations are what tells an Arrow function apart."""
    function.__annotations__ = dict(zip((*function.__code__.co_varnames[: function.__code__.co_argcount], "return"), kinds, strict=True))
    return function


def key_column(key: pa.Array, params: Params) -> tuple[np.ndarray, pa.Array]:
    """Places of the keys that aren't null, and their canonical encoding."""
    some = np.flatnonzero(key.is_valid().to_numpy(zero_copy_only=False))
    return some, pa.array([encoded_string(x, params.max_bytes) for x in key.take(pa.array(some)).cast(pa.binary()).to_pylist()], pa.binary())


class Evaluator:
    """Answers for string keys; made on first use in each task from rows that were sent once."""

    def __init__(self, artifact: Artifact):
        if artifact.params.native:
            raise ValueError("use lookup() for the native family")
        if stored_bytes(artifact) > BROADCAST_BYTES:
            raise ValueError("the artifact is too large to travel; use lookup() in partitioned mode")
        self.rows = artifact.rows.sparkSession.sparkContext.broadcast([r.asDict() for r in artifact.rows.collect()])
        self.params, self.attempt, self.b = artifact.params, artifact.attempt, artifact.b
        self.functions = None

    def __getstate__(self) -> dict:
        return self.__dict__ | {"functions": None}

    def __call__(self, key: pa.Array, which: int) -> np.ndarray:
        """Slots (0) or ids (1), -1 for null and for empty buckets."""
        if self.functions is None:
            self.functions = functions_of(self.rows.value, self.params)
        some, data = key_column(key, self.params)
        full = np.full(len(key), -1)
        if len(some):
            full[some] = _answers(self.functions, words_of(data, self.params, self.attempt)[:, : word_count(self.params)], self.b, self.params, self.attempt)[which]
        return full


def register_lookup(spark: SparkSession, name: str, artifact: Artifact, slot: bool = False) -> None:
    """A SQL function from a string key to its id, or to its slot; null for null and for empty buckets.

    Only families that hash in Python can be called so; artifacts that are too large to travel are refused."""
    evaluate, which = Evaluator(artifact), 0 if slot else 1

    def found(key):
        full = evaluate(key, which)
        return pa.array(full, mask=full < 0)

    spark.udf.register(name, F.arrow_udf(_named(found, pa.Array, pa.Array), T.LongType()))


def register_iterator_lookup(spark: SparkSession, name: str, artifact: Artifact) -> None:
    """The same as a pandas function over an iterator of batches, whose artifact is read once for each task."""
    evaluate = Evaluator(artifact)

    @F.pandas_udf("long")
    def found(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for keys in batches:
            full = evaluate(pa.array(keys, pa.string(), from_pandas=True), 1)
            yield pd.Series(full).astype("Int64").mask(full < 0)

    spark.udf.register(name, found)


def register_membership(spark: SparkSession, name: str, members: SlotFilter) -> None:
    """A SQL function from a string key to whether it may be a member; null for null."""
    evaluate = Evaluator(members.artifact)
    table = members.signatures.toArrow()
    packed = np.zeros(max(1, members.artifact.n), np.int32)
    packed[table.column("id").to_numpy()] = table.column("signature").to_numpy()
    shared, bits = spark.sparkContext.broadcast(packed), members.bits

    def maybe(key, mine):
        ids = evaluate(key, 1)
        told = (ids >= 0) & (shared.value[np.maximum(ids, 0)] == mine.fill_null(-1).to_numpy(zero_copy_only=False))
        return pa.array(told, mask=~key.is_valid().to_numpy(zero_copy_only=False))

    spark.udf.register(f"{name}_of", F.arrow_udf(_named(maybe, pa.Array, pa.Array, pa.Array), T.BooleanType()))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(k STRING) RETURNS BOOLEAN RETURN {name}_of(k, {signature_of('k', bits, members.artifact.params.max_bytes)})")


def register_hashes(spark: SparkSession, params: Params = Params()) -> None:
    """`key_fp128(key)`: the fingerprint of a string key as a struct of two longs; `gf2_parity(x, row)`: the parity of two longs' common bits."""

    def key_fp128(key):
        some, data = key_column(key, params)
        hi, lo = np.zeros(len(key), np.int64), np.zeros(len(key), np.int64)
        if len(some):
            hi[some], lo[some] = as_longs(words_of(data, params, 0))
        return pa.StructArray.from_arrays([pa.array(hi), pa.array(lo)], ["hi", "lo"], mask=pa.array(~key.is_valid().to_numpy(zero_copy_only=False)))

    def gf2_parity(x, row):
        both = x.fill_null(0).to_numpy(zero_copy_only=False) & row.fill_null(0).to_numpy(zero_copy_only=False)
        return pa.array(np.bitwise_count(both.view(np.uint64)).astype(np.int64) & 1, mask=~(x.is_valid().to_numpy(zero_copy_only=False) & row.is_valid().to_numpy(zero_copy_only=False)))

    spark.udf.register("key_fp128", F.arrow_udf(_named(key_fp128, pa.Array, pa.Array), T.StructType([T.StructField("hi", T.LongType()), T.StructField("lo", T.LongType())])))
    spark.udf.register("gf2_parity", F.arrow_udf(_named(gf2_parity, pa.Array, pa.Array, pa.Array), T.LongType()))


def register_bucket_bits(spark: SparkSession, eps: float = 0.045) -> None:
    """`bits_of_bucket(key)`: an aggregate over the keys of a bucket, the bits of its minimal function."""
    from densekeys.measures import bucket_bits

    @F.pandas_udf("long")
    def bits_of_bucket(keys: pd.Series) -> int:
        return bucket_bits(keys.nunique(), eps)[1]

    spark.udf.register("bits_of_bucket", bits_of_bucket)


@F.udtf(returnType="place int")
class SetPlaces:
    """Places of the set bits of a bit vector of little-endian words, as rows."""

    def eval(self, bits: bytes):
        for place in np.flatnonzero(np.unpackbits(np.frombuffer(bits, np.uint8), bitorder="little")).tolist():
            yield (place,)


@F.udtf(returnType="bucket long, size long, tries long")
class ArtifactBuckets:
    """The buckets packed in one row of an artifact."""

    def eval(self, buckets: bytes, sizes: bytes, tries: bytes):
        yield from zip(*(np.frombuffer(x, np.int64).tolist() for x in (buckets, sizes, tries)), strict=True)


@F.udtf(returnType="round int, edge int, leaf int")
class PeelTrace:
    """What peeling takes from a graph, round by round: edges by their place, and the end that each is taken with."""

    def eval(self, left: list, right: list):
        a, b = np.array(left, np.int64), np.array(right, np.int64)
        _, rounds = peel(a, b, int(max(a.max(initial=-1), b.max(initial=-1))) + 1)
        for k, (edges, leaves) in enumerate(rounds):
            for edge, leaf in zip(edges.tolist(), leaves.tolist(), strict=True):
                yield k, edge, leaf


def register_tables(spark: SparkSession) -> None:
    for name, table in (("set_places", SetPlaces), ("artifact_buckets", ArtifactBuckets), ("peel_trace", PeelTrace)):
        spark.udtf.register(name, table)
