"""Objects sent once to each executor; names of columns."""

from __future__ import annotations

from pyspark import SparkContext, cloudpickle
from pyspark.sql import DataFrame

#: What names of the operators' own columns begin with.
OWN = "ml_"


class Shared:
    """A broadcast that carries its classes with it, and whose value a task can let go of and load again."""

    def __init__(self, sc: SparkContext, value):
        self._held = sc.broadcast(cloudpickle.dumps(value))
        self._value = None

    def __getstate__(self):
        return self._held

    def __setstate__(self, held):
        self._held, self._value = held, None

    @property
    def value(self):
        if self._value is None:
            self._value = cloudpickle.loads(self._held.value)
            if hasattr(self._held, "_path") and hasattr(self._held, "_value"):
                del self._held._value  # the packed form; on executors it is read again from their own copy
        return self._value

    def release(self) -> None:
        self._value = None


def aside(docs: DataFrame) -> tuple[DataFrame, dict[str, str]]:
    """docs with the columns that begin as the operators' own do under other names, and the present name of each column."""
    taken, names = {c.lower() for c in docs.columns}, {}
    for c in docs.columns:
        new = c
        while new.lower().startswith(OWN) or (new != c and new.lower() in taken):
            new = f"given_{new}"
        taken.add(new.lower())
        names[c] = new
    return docs.toDF(*names.values()), names
