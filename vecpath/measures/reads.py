"""What a plan reads from files: counted by the scans themselves while the plan runs."""

from __future__ import annotations

from pyspark.sql import DataFrame

COUNTED = {"rows": "numOutputRows", "files": "numFiles", "bytes": "filesSize"}


def _scans(node, found: list) -> None:
    kind = node.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        return _scans(node.executedPlan(), found)
    if kind.endswith("QueryStageExec"):
        return _scans(node.plan(), found)
    if kind == "ReusedExchangeExec":
        return None
    if kind == "FileSourceScanExec":
        found.append(node.metrics())
    children = node.children()
    for i in range(children.size()):
        _scans(children.apply(i), found)
    return None


def reads(df: DataFrame) -> dict[str, int]:
    """Rows, files and bytes of files that the scans of ``df`` read, summed over scans; runs the plan."""
    run = df._jdf.queryExecution()
    run.toRdd().count()
    found: list = []
    _scans(run.executedPlan(), found)
    value = lambda m, name: m.apply(name).value() if m.contains(name) else 0
    return {k: sum(value(m, name) for m in found) for k, name in COUNTED.items()}
