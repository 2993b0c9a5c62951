"""The generic worker: runs stored functions on rows of an Arrow batch under limits and retries."""

from __future__ import annotations

import os
import shutil
import signal
import tempfile
import threading
import time
from collections.abc import Callable

from callweave.calls.closure import unpack_closure
from callweave.calls.spec import CallLimits, RetryPolicy


class CallTimeout(Exception):
    pass


def _expire(signum, frame):
    raise CallTimeout


def _folder_mb(path: str) -> float:
    return sum(os.path.getsize(os.path.join(d, f)) for d, _, fs in os.walk(path) for f in fs) / 1e6


def guarded_call(fn: Callable, value, limits: CallLimits | None):
    """(status, result, error) of one run: ok, failed, timed_out, over_memory or over_scratch."""
    if limits is None:
        try:
            return "ok", fn(value), None
        except Exception as e:
            return "failed", None, e
    import resource

    timed = threading.current_thread() is threading.main_thread()
    old_limit = resource.getrlimit(resource.RLIMIT_AS)
    used = int(open("/proc/self/statm").read().split()[0]) * resource.getpagesize() if os.path.exists("/proc/self/statm") else 0
    cap = used + limits.memory_mb * 1_000_000
    if old_limit[1] != resource.RLIM_INFINITY:
        cap = min(cap, old_limit[1])
    scratch = tempfile.mkdtemp(prefix="call-")
    before, os.environ["CALL_SCRATCH"] = os.environ.get("CALL_SCRATCH"), scratch
    if timed:
        old = signal.signal(signal.SIGALRM, _expire)
        signal.setitimer(signal.ITIMER_REAL, limits.seconds)
    try:
        resource.setrlimit(resource.RLIMIT_AS, (cap, old_limit[1]))
        result = fn(value)
        if _folder_mb(scratch) > limits.scratch_mb:
            return "over_scratch", None, RuntimeError(f"more than {limits.scratch_mb} MB of scratch files")
        return "ok", result, None
    except CallTimeout as e:
        return "timed_out", None, e
    except MemoryError as e:
        return "over_memory", None, e
    except Exception as e:
        return "failed", None, e
    finally:
        if timed:
            signal.setitimer(signal.ITIMER_REAL, 0)
            signal.signal(signal.SIGALRM, old)
        resource.setrlimit(resource.RLIMIT_AS, old_limit)
        shutil.rmtree(scratch, ignore_errors=True)
        if before is None:
            os.environ.pop("CALL_SCRATCH", None)
        else:
            os.environ["CALL_SCRATCH"] = before


def call_with_retry(get_fn: Callable[[], Callable], value, limits: CallLimits | None, retry: RetryPolicy):
    """(attempts, status, result, error text, milliseconds); a retried call sees the same input."""
    began = time.perf_counter()
    for attempt in range(1, retry.max_attempts + 1):
        status, result, error = guarded_call(get_fn(), value, limits)
        if status == "ok" or not isinstance(error, retry.retry_on):
            break
        if attempt < retry.max_attempts and retry.backoff_ms:
            time.sleep(retry.backoff_ms / 1000 * 2 ** (attempt - 1))
    text = None if error is None else f"{type(error).__name__}: {error}"[:2000]
    return attempt, status, result, text, (time.perf_counter() - began) * 1000


class CodeCache:
    """Functions by id. "fresh" unpickles the code for every call, so nothing a call does to it outlives the call."""

    def __init__(self, code: dict[str, bytes], isolation: str):
        self.code, self.fresh, self.loaded = code, isolation == "fresh", {}

    def getter(self, fn_id: str) -> Callable[[], Callable]:
        if self.fresh:
            return lambda: unpack_closure(self.code[fn_id])
        if fn_id not in self.loaded:
            self.loaded[fn_id] = unpack_closure(self.code[fn_id])
        return lambda: self.loaded[fn_id]


def call_attempt(fn_with_attempt: Callable) -> Callable:
    """Wrap f(value, attempt) as f(value) whose attempt counts runs on the same value; for fault injection in tests."""
    seen: dict = {}

    def run(value):
        seen[value] = seen.get(value, 0) + 1
        return fn_with_attempt(value, seen[value])

    return run
