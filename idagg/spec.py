"""What a request asks for and what a stored state stands for."""

from __future__ import annotations

from dataclasses import asdict, dataclass, field, replace

DEFAULT_P = 11  # 2,048 one-byte registers


@dataclass(frozen=True)
class OperandSpec:
    """One operand stream of a table: which records, what names their identity, and optionally their group and segment.

    All four are SQL expressions over the table's columns."""

    stream_id: str
    identity: str
    where: str = "true"
    group: str | None = None
    segment: str | None = None
    event_time: str | None = None


@dataclass(frozen=True)
class Request:
    """An operator over operand streams: distinct, union, jaccard, containment, overlap, grouped_distinct or frequency."""

    op: str
    operands: tuple[str, ...]
    groups: tuple[str, ...] | None = None
    probe: str | None = None


@dataclass(frozen=True)
class StateDescriptor:
    """States may be merged or related only where all of this agrees (the stream differs between the two sides of a relation)."""

    p: int = DEFAULT_P
    family: str = "md5"
    seed: int = 0
    identity_def: str = ""
    stream_def: str = ""
    version: int = 1

    @property
    def m(self) -> int:
        return 1 << self.p

    def as_dict(self) -> dict:
        return asdict(self)

    def for_stream(self, spec: OperandSpec) -> StateDescriptor:
        return replace(self, identity_def=spec.identity, stream_def=f"{spec.where} | {spec.group}")


class IncompatibleStates(ValueError):
    pass


def assert_compatible(a: StateDescriptor, b: StateDescriptor, same_stream: bool = False) -> None:
    """Raise unless states under a and b may be merged (same_stream) or related."""
    names = ["p", "family", "seed", "identity_def", "version"] + ["stream_def"] * same_stream
    differ = [n for n in names if getattr(a, n) != getattr(b, n)]
    if differ:
        raise IncompatibleStates(f"states differ in {', '.join(differ)}")


@dataclass(frozen=True)
class Plan:
    """Requests grouped so that each operand is scanned and built once."""

    operands: tuple[OperandSpec, ...]
    requests: tuple[Request, ...]
    descriptor: StateDescriptor = field(default_factory=StateDescriptor)
