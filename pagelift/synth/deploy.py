"""Deployment of a generated reader: the sources run it in place of the built-in decoder.

A source given as an option is run by executors.  So a scan takes one only with the option `allow_generated`, which
whoever writes the scan has to set; `options` sets both for a result that passed its checks.
"""

from __future__ import annotations

import base64
import functools
import zlib

from pagelift.synth.loop import SynthResult


def deploy(result: SynthResult) -> str:
    """A value for the sources' option `reader`: the source itself, so that no executor needs another file."""
    if not result.passed:
        raise ValueError(f"{result.name} has no reader that passed")
    return base64.b64encode(zlib.compress(result.source.encode())).decode()


def options(result: SynthResult) -> dict[str, str]:
    """Options of a scan that reads through the result's reader."""
    return {"reader": deploy(result), "allow_generated": "true"}


@functools.lru_cache(maxsize=64)
def load(option: str):
    """The entry function, compiled once a worker."""
    from pagelift.synth.qa import compiled

    return compiled(zlib.decompress(base64.b64decode(option)).decode())
