"""The portal as a Spark data source: ``df.write.format("portal")`` sends changes over HTTP; dry runs only count.

Options: url, key (needed for writes, never logged or shown in plans), dry_run (default true), batch, retries, log (a folder where a
dry run leaves one line per task).
"""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql.datasource import DataSource, DataSourceWriter, WriterCommitMessage


@dataclass
class Sent(WriterCommitMessage):
    rows: int
    calls: int


class PortalWriter(DataSourceWriter):
    def __init__(self, options: dict[str, str]):
        self.url, self.batch, self.retries = options.get("url", ""), int(options.get("batch", "100")), int(options.get("retries", "3"))
        self.dry_run, self._key = options.get("dry_run", "true").lower() == "true", options.get("key", "")
        self.log = options.get("log")
        if not self.dry_run and not self._key:
            raise ValueError("writing to the portal needs a key")

    def __repr__(self) -> str:
        return f"PortalWriter({self.url}, dry_run={self.dry_run})"

    def _send(self, rows: list[dict]) -> None:
        if self.dry_run:
            return
        from urllib.request import Request, urlopen

        body = json.dumps(rows).encode()
        for attempt in range(self.retries):
            try:
                urlopen(Request(self.url, body, {"Content-Type": "application/json", "Authorization": f"Bearer {self._key}"}), timeout=60).close()
                return
            except OSError:
                if attempt + 1 == self.retries:
                    raise

    def write(self, iterator) -> Sent:
        """Each request carries (op, item_id, digest, body): the portal applies it once per digest, so task retries are harmless."""
        rows, n, calls = [], 0, 0
        for row in iterator:
            rows.append(row.asDict())
            n += 1
            if len(rows) == self.batch:
                self._send(rows)
                rows, calls = [], calls + 1
        if rows:
            self._send(rows)
            calls += 1
        return Sent(n, calls)

    def commit(self, messages: list) -> None:
        if self.log:
            with open(self.log, "w") as f:
                json.dump({"rows": sum(m.rows for m in messages if m), "calls": sum(m.calls for m in messages if m)}, f)

    def abort(self, messages: list) -> None:
        return None


class PortalSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "portal"

    def writer(self, schema, overwrite: bool) -> PortalWriter:
        return PortalWriter(dict(self.options))


def register(spark) -> None:
    spark.dataSource.register(PortalSource)
