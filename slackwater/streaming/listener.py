"""What streams report: rows and seconds of each trigger, for the rate monitor and the run log."""

from __future__ import annotations

from pyspark.sql.streaming import StreamingQueryListener


class TriggerLog(StreamingQueryListener):
    """Keeps (query name, batch, rows, milliseconds) of every trigger."""

    def __init__(self):
        self.rows: list[tuple[str, int, int, int]] = []

    def onQueryStarted(self, event) -> None:
        pass

    def onQueryProgress(self, event) -> None:
        p = event.progress
        self.rows.append((p.name, p.batchId, p.numInputRows, p.batchDuration))

    def onQueryIdle(self, event) -> None:
        pass

    def onQueryTerminated(self, event) -> None:
        pass
