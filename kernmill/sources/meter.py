"""What really passed: rows and bytes of every exchange of an executed plan."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

STAGES = ("ShuffleQueryStageExec", "BroadcastQueryStageExec", "ResultQueryStageExec", "TableCacheQueryStageExec")


@dataclass(frozen=True)
class Passed:
    """One shuffle: rows, bytes before compression, and the words of 8 bytes beyond the fixed part of each row."""

    rows: int
    bytes: int
    columns: int

    @property
    def words(self) -> int:
        """Variable-length payload: a row holds 8 bytes of null bits (for up to 64 columns) and 8 a column before it."""
        return (self.bytes - self.rows * 8 * (1 + self.columns)) // 8


def _metric(plan, name: str) -> int:
    return int(plan.metrics().apply(name).value())


def _exchanges(plan, into_cache: bool):
    name = plan.getClass().getSimpleName()
    if name == "AdaptiveSparkPlanExec":
        yield from _exchanges(plan.executedPlan(), into_cache)
    elif name in STAGES:
        yield from _exchanges(plan.plan(), into_cache)
    elif name == "InMemoryTableScanExec":
        if into_cache:
            yield from _exchanges(plan.relation().cachedPlan(), False)
    else:
        if name == "ShuffleExchangeExec":
            yield plan
        children = plan.children()
        for i in range(children.size()):
            yield from _exchanges(children.apply(i), into_cache)


def _found(df: DataFrame, into_cache: bool):
    return _exchanges(df._jdf.queryExecution().executedPlan(), into_cache)


def shuffles(df: DataFrame, into_cache: bool = False) -> list[Passed]:
    """Shuffles of a frame that has been run by ``collect``, from the result down; those of the cached frame under it on request."""
    return [Passed(_metric(e, "shuffleRecordsWritten"), _metric(e, "dataSize"), e.output().size()) for e in _found(df, into_cache)]


def _drop(df: DataFrame, into_cache: bool) -> None:
    cleaner = df.sparkSession.sparkContext._jsc.sc().cleaner()
    if cleaner.isDefined():
        for e in _found(df, into_cache):
            cleaner.get().doCleanupShuffle(e.shuffleDependency().shuffleId(), True)


def drop_files(df: DataFrame) -> None:
    """Removes the files of the shuffles that filled the cached frame under ``df``; else they stay until the driver happens to collect its garbage."""
    _drop(df, True)


def drop_run(df: DataFrame, kept: DataFrame | None = None) -> None:
    """As ``drop_files``, for a frame that has been run and is not read again: its own shuffles, and those that filled ``kept`` under it."""
    _drop(df, False)
    if kept is not None:
        _drop(kept.select(kept.columns[0]), True)
