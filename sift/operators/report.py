"""What a query really read: file and row counts of its scans, and comparisons of runs."""

from __future__ import annotations

import inspect
import time
from dataclasses import dataclass

from pyspark.sql import DataFrame

from sift.operators import kinds as kinds_module
from sift.session import SiftSession


@dataclass
class Scan:
    files: int
    bytes: int
    rows: int


def scans(df: DataFrame) -> list[Scan]:
    """The file scans of an executed plan; run an action on this very DataFrame first."""
    found: list[Scan] = []

    def visit(node) -> None:
        name = node.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            return visit(node.executedPlan())
        if name.endswith("QueryStageExec"):
            return visit(node.plan())
        if name == "FileSourceScanExec":
            m = node.metrics()
            value = lambda k: int(m.apply(k).value()) if m.contains(k) else 0
            found.append(Scan(value("numFiles"), value("filesSize"), value("numOutputRows")))
        kids = node.children()
        for i in range(kids.size()):
            visit(kids.apply(i))

    visit(df._jdf.queryExecution().executedPlan())
    return found


@dataclass
class SkipReport:
    """One query with and without skipping."""

    objects: int
    skipped: int
    bytes: int
    bytes_skipped: int
    summary_seconds: float
    data_seconds: float
    baseline_seconds: float
    #: Bytes of the summaries that the test reads.
    metadata_bytes: int = 0


def metadata_bytes(session: SiftSession, made: list) -> int:
    """Bytes of summaries that some decisions read."""
    return sum(session.lakes[d.lake].store.read_bytes(d.test.needs()) for d in made if d.test.needs())


def skip_report(session: SiftSession, text: str) -> SkipReport:
    """Run ``text`` under the session and without skipping."""
    before = len(session.history)
    began = time.time()
    df = session.sql(text)
    planned = time.time()
    df.collect()
    ran = time.time()
    made = session.history[before:]
    plain = SiftSession(session.spark, skipping=False)
    plain.lakes = session.lakes
    at = time.time()
    plain.sql(text).collect()
    return SkipReport(sum(d.objects for d in made), sum(d.objects - d.n_kept for d in made), sum(d.bytes for d in made), sum(d.bytes - d.bytes_kept for d in made), planned - began, ran - planned, time.time() - at, metadata_bytes(session, made))


def kind_line_counts() -> dict[str, int]:
    """Source lines of each kind with its matcher: what a new kind takes."""
    classes = {n: c for n, c in vars(kinds_module).items() if inspect.isclass(c) and issubclass(c, kinds_module.SummaryKind) and c is not kinds_module.SummaryKind}
    return {n: sum(bool(line.strip()) for line in inspect.getsource(c).splitlines()) for n, c in classes.items()}
