"""Ports: how a component written item by item meets its neighbours.

A pulled neighbour is asked whether there is more and then for the next item; a pushed one is handed items. Items cross to
the engine in batches, so a component's body may be imperative while its streams stay bounded.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from pipeflow.plans.parallel import BATCH
from pipeflow.plans.pipeline import Component, Context


class PullPort:
    """The side that a component takes from. Holds one batch at a time."""

    def __init__(self, batches: Iterator[pa.RecordBatch]):
        self.batches, self.held, self.at = batches, [], 0

    def more(self) -> bool:
        while self.at == len(self.held):
            batch = next(self.batches, None)
            if batch is None:
                return False
            self.held, self.at = batch.to_pylist(), 0
        return True

    def peek(self) -> dict:
        if not self.more():
            raise EOFError("the stream has ended")
        return self.held[self.at]

    def take(self) -> dict:
        item = self.peek()
        self.at += 1
        return item


class PushPort:
    """The side that a component delivers to."""

    def __init__(self, schema: pa.Schema):
        self.schema, self.held = schema, []

    def deliver(self, item: dict) -> None:
        self.held.append(item)

    def flush(self) -> pa.RecordBatch:
        out = pa.RecordBatch.from_pylist(self.held, self.schema)
        self.held = []
        return out


class Items(Component):
    """A component whose body f(pull, push) is called as long as there is more; each call takes one item at least.

    Runs in each partition by itself. What it delivers is handed on in batches of `batch` items.
    """

    def __init__(self, f: Callable[[PullPort, PushPort], None], schema: str, name: str | None = None, batch: int = BATCH):
        super().__init__(name)
        self.f, self.schema, self.batch = f, schema, batch

    def plan(self, ctx: Context, inputs: list[DataFrame]) -> DataFrame:
        from pyspark.sql.pandas.types import to_arrow_schema
        from pyspark.sql.types import _parse_datatype_string

        f, batch, arrow = self.f, self.batch, to_arrow_schema(_parse_datatype_string(self.schema))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            pull, push = PullPort(batches), PushPort(arrow)
            while pull.more():
                f(pull, push)
                if len(push.held) >= batch:
                    yield push.flush()
            yield push.flush()

        return inputs[0].mapInArrow(run, self.schema)
