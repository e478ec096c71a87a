"""Which failures are worth another try: interruptions and I/O, not errors of the application."""

from __future__ import annotations

import re
from collections.abc import Callable

_RECOVERABLE = re.compile(r"java\.io\.|IOException|FetchFailed|ExecutorLost|executor .*(lost|exited)|Interrupted|Connection (reset|refused)|HeartbeatTimeout", re.I)
_APPLICATION = re.compile(r"PythonException|AnalysisException|ArithmeticException|SparkRuntimeException|DIVIDE_BY_ZERO|CAST_INVALID")


class FailurePolicy:
    def __init__(self, most_retries: int = 3):
        self.most_retries = most_retries

    def recoverable(self, error: BaseException) -> bool:
        said = f"{type(error).__name__}: {error}"
        return isinstance(error, (OSError, InterruptedError)) or bool(_RECOVERABLE.search(said)) and not _APPLICATION.search(said)

    def run(self, attempt: Callable[[], object]):
        """Call ``attempt`` until it ends well, a failure isn't recoverable, or retries are used up."""
        for left in range(self.most_retries, -1, -1):
            try:
                return attempt()
            except Exception as error:
                if not left or not self.recoverable(error):
                    raise
        return None
