"""Functions as bytes: packing with captured state, and a report of what can't be packed."""

from __future__ import annotations

import hashlib
import inspect
from collections.abc import Callable
from dataclasses import dataclass

from pyspark import cloudpickle


class ClosureError(ValueError):
    """A function can't be shipped; the message names the captured values at fault."""


@dataclass(frozen=True)
class PackedClosure:
    data: bytes
    fn_id: str
    name: str


def closure_report(fn: Callable) -> list[tuple[str, str, str]]:
    """(where, name, "ok" or the error) for each value that `fn` captures."""
    captured = inspect.getclosurevars(fn)
    out = []
    for where, values in (("closure", captured.nonlocals), ("global", captured.globals)):
        for name, value in sorted(values.items()):
            try:
                cloudpickle.dumps(value)
                out.append((where, name, "ok"))
            except Exception as e:
                out.append((where, name, f"{type(e).__name__}: {e}"))
    return out


def pack_closure(fn: Callable) -> PackedClosure:
    try:
        data = cloudpickle.dumps(fn)
    except Exception as e:
        try:
            bad = [f"{where} {name}" for where, name, state in closure_report(fn) if state != "ok"]
        except TypeError:
            bad = []
        raise ClosureError(f"{getattr(fn, '__name__', fn)!s} can't be serialised: {', '.join(bad) or e}") from e
    return PackedClosure(data, hashlib.sha256(data).hexdigest()[:24], getattr(fn, "__name__", "call"))


def unpack_closure(data: bytes) -> Callable:
    return cloudpickle.loads(data)
