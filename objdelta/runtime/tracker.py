"""Access tracking: which names a block of code reads, writes and deletes."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass
class Execution:
    code: str
    accessed: set[str] = field(default_factory=set)
    written: set[str] = field(default_factory=set)
    deleted: set[str] = field(default_factory=set)

    @property
    def touched(self) -> set[str]:
        return self.accessed | self.written


class TrackedNames(dict):
    """A namespace that records key access while a block runs."""

    def __init__(self, names: dict, execution: Execution, on_access=None):
        super().__init__(names)
        self._execution, self._on_access = execution, on_access or (lambda name: None)

    def __getitem__(self, name):
        if name in self.keys():
            self._on_access(name)
            self._execution.accessed.add(name)
        return super().__getitem__(name)

    def __setitem__(self, name, value):
        self._on_access(name)
        self._execution.written.add(name)
        super().__setitem__(name, value)

    def __delitem__(self, name):
        self._execution.deleted.add(name)
        super().__delitem__(name)


class Tracker:
    def __init__(self, enabled: bool = True):
        self.enabled = enabled

    def run(self, code: str, names: dict, on_access=None) -> Execution:
        """Run the block over the namespace, which it changes in place."""
        execution = Execution(code)
        hidden = {"__builtins__": __builtins__}
        if not self.enabled:
            exec(compile(code, "<block>", "exec"), hidden, names)
            execution.accessed = set(names)
            return execution
        tracked = TrackedNames(names, execution, on_access)
        exec(compile(code, "<block>", "exec"), hidden, tracked)
        names.clear()
        names.update(dict(tracked))
        return execution


def tables_of(spark, sql: str) -> set[str]:
    """Tables and views that a SQL statement names, from its unresolved plan."""
    import re

    plan = spark._jsparkSession.sessionState().sqlParser().parsePlan(sql).toString()
    return {m.split(",")[0].strip().split(".")[-1].strip("`]") for m in re.findall(r"UnresolvedRelation \[([^\]]+)\]", plan)}
