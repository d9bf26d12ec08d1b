"""Token counts kept as additive totals by source, language and tokenizer version.

A batch of signed changes (+1 a row that comes, -1 a row that goes; a revision is both) is counted, summed up and
committed under its batch id: its sums are written aside and take their place by one rename, so a batch counts wholly or not at all and of two writers
of one id one wins. A batch that is committed again changes nothing. Each commit then folds what is new into the
next version of the totals, likewise by one rename; reading takes the latest version and the commits that it lacks. Earlier
versions stay and can be read as of then. ``compact`` starts anew from the totals.

A null text counts as empty (no tokens); null sources and languages form groups of their own; a null sign counts as +1; repeated rows count each
time; other columns are ignored. A batch without rows commits nothing but its id.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from urllib.parse import quote, unquote

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathlore.llm.bpe import encoder
from pathlore.llm.common import shared_path

KEYS = ("source", "lang", "tokenizer")
SUMS = ("n_docs", "n_tokens", "n_bytes")
SCHEMA = "source string, lang string, tokenizer string, n_docs long, n_tokens long, n_bytes long"
#: Groups that a task sums up before it hands them on.
HELD = 100_000


def count_words(texts: list[str]) -> list[int]:
    return [len(t.encode().split()) for t in texts]


def count_bpe(path: str) -> Callable[[list[str]], list[int]]:
    return lambda texts: [len(ids) for ids in encoder(path).encode_batch(texts)]


def batch_sums(changes: DataFrame, tokenizers: dict[str, Callable[[list[str]], list[int]]]) -> DataFrame:
    """The signed sums of ``changes`` (source, lang, text, sign): summed within each task before the shuffle."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple, list[int]] = {}

        def out() -> pa.RecordBatch:
            cols, vals = ([*zip(*x, strict=True)] if sums else [[]] * 3 for x in (sums, sums.values()))
            return pa.RecordBatch.from_arrays([*(pa.array(c, pa.string()) for c in cols), *(pa.array(v, pa.int64()) for v in vals)], [*KEYS, *SUMS])

        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                texts = [t or "" for t in part.column("text").to_pylist()]
                sizes = [len(t.encode()) for t in texts]
                for name, count in tokenizers.items():
                    for s, lang, sign, n, size in zip(part.column("source").to_pylist(), part.column("lang").to_pylist(), part.column("sign").to_pylist(), count(texts), sizes, strict=True):
                        row = sums.setdefault((s, lang, name), [0, 0, 0])
                        row[0] += sign
                        row[1] += sign * n
                        row[2] += sign * size
                if len(sums) > HELD:
                    yield out()
                    sums.clear()
        yield out()

    sign = F.coalesce(F.col("sign"), F.lit(1)) if "sign" in changes.columns else F.lit(1)
    rows = changes.select("source", "lang", "text", sign.cast("int").alias("sign")).mapInArrow(work, SCHEMA)
    return rows.groupBy(*KEYS).agg(*(F.sum(c).alias(c) for c in SUMS))


class TokenRollup:
    """Commits under ``path``/batch=..., versions of the totals under ``path``/totals=... with the ids that they hold."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self._path = spark._jvm.org.apache.hadoop.fs.Path
        root = self._path(self.path)
        self._fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
        self._fs.mkdirs(root)

    def _named(self, kind: str) -> list[str]:
        found = [f.getPath().getName() for f in self._fs.listStatus(self._path(self.path)) if f.isDirectory()]
        return sorted(unquote(n.removeprefix(kind)) for n in found if n.startswith(kind))

    def _place(self, name: str, tables: dict[str, DataFrame]) -> bool:
        """Write the tables aside, then give them their name by one rename; False if the name is taken."""
        target, aside = self._path(f"{self.path}/{name}"), f"aside-{uuid.uuid4().hex}"
        if self._fs.exists(target):
            return False
        for table, rows in tables.items():
            rows.write.parquet(f"{self.path}/{aside}/{table}")
        source = self._path(f"{self.path}/{aside}")
        moved, inside = self._fs.rename(source, target), self._path(target, aside)
        lost = not moved or self._fs.exists(inside)  # a rename onto a folder moves into it: another writer was first
        self._fs.delete(source, True)
        self._fs.delete(inside, True)
        return not lost

    def _read(self, *tables: str) -> DataFrame:
        return self.spark.read.schema(SCHEMA).parquet(*(f"{self.path}/{t}" for t in tables)) if tables else self.spark.createDataFrame([], SCHEMA)

    def versions(self) -> list[int]:
        return sorted(map(int, self._named("totals=")))

    def _held(self, version: int | None) -> set[str]:
        """The batch ids in a version."""
        return {r.batch for r in self.spark.read.schema("batch string").parquet(f"{self.path}/totals={version}/batches").collect()} if version is not None else set()

    def committed(self) -> list[str]:
        latest = self.versions()[-1:]
        return sorted(self._held(latest[0] if latest else None) | set(self._named("batch=")))

    def commit(self, batch_id: str, changes: DataFrame, tokenizers: dict[str, Callable[[list[str]], list[int]]]) -> bool:
        """Count and commit; False if the batch was committed before."""
        if batch_id in self.committed():
            return False
        done = self._place(f"batch={quote(batch_id, safe='')}", {"sums": batch_sums(changes, tokenizers)})
        self.fold()
        return done

    def fold(self) -> None:
        """Write the next version of the totals if there are commits that the latest lacks."""
        version = (self.versions() or [None])[-1]
        held, all_ = self._held(version), set(self.committed())
        if all_ - held:
            names = self.spark.createDataFrame([(b,) for b in sorted(all_)], "batch string")
            self._place(f"totals={0 if version is None else version + 1}", {"sums": self._totals(version, all_ - held), "batches": names})

    def _totals(self, version: int | None, more: set[str]) -> DataFrame:
        rows = self._read(*([] if version is None else [f"totals={version}/sums"]), *(f"batch={quote(b, safe='')}/sums" for b in sorted(more)))
        return rows.groupBy(*KEYS).agg(*(F.sum(c).alias(c) for c in SUMS)).where("n_docs <> 0 or n_tokens <> 0 or n_bytes <> 0")

    def totals(self, version: int | None = None) -> DataFrame:
        """The totals now, or as of a version."""
        if version is not None:
            return self._totals(version, set())
        latest = (self.versions() or [None])[-1]
        return self._totals(latest, set(self.committed()) - self._held(latest))

    def compact(self, into: str) -> TokenRollup:
        """A new rollup that holds the totals as its first version, and the batch ids."""
        out = TokenRollup(self.spark, into)
        names = self.spark.createDataFrame([(b,) for b in self.committed()], "batch string")
        out._place("totals=0", {"sums": self.totals(), "batches": names})
        return out


def fresh_rollup(spark: SparkSession) -> TokenRollup:
    return TokenRollup(spark, shared_path(spark, "rollup"))
