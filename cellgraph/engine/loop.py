"""What a bulk-synchronous run did."""

from __future__ import annotations

from dataclasses import dataclass, field


@dataclass
class Run:
    """One entry per superstep, the first included.

    A superstep counts when it invokes at least one unit; the one in which nothing changes any more
    counts as well.  ``messages`` are those generated in it; ``combined`` those that travel after the
    sender has merged what goes to one target; ``crossing`` those of them that leave their part;
    ``work`` is what a program counts itself (settled vertices, scanned arcs); ``reports`` what its
    calls report in sum in the second slot.
    """

    messages: list[int] = field(default_factory=list)
    combined: list[int] = field(default_factory=list)
    crossing: list[int] = field(default_factory=list)
    work: list[int] = field(default_factory=list)
    reports: list[float] = field(default_factory=list)

    def step(self, messages: int, combined: int, crossing: int = 0, work: int = 0, report: float = 0.0) -> None:
        self.messages.append(messages)
        self.combined.append(combined)
        self.crossing.append(crossing)
        self.work.append(work)
        self.reports.append(report)

    @property
    def supersteps(self) -> int:
        return len(self.messages)

    @property
    def total_messages(self) -> int:
        return sum(self.messages)
