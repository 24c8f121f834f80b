"""Coders: specification and feedback -> source of a stand-alone reader with a fixed entry function.

There is no language model here, so coders are deterministic.  `TemplateCoder` writes a reader that serves any schema;
`FaultyCoder` seeds known faults that feedback removes one by one, to exercise the loop; `ExternalCoder` runs a command.
"""

from __future__ import annotations

import json
import re
import subprocess
from dataclasses import asdict, dataclass, field
from typing import Protocol

from pagelift.synth import templates
from pagelift.synth.spec import FormatSpec

ENTRY = "read_pages"


@dataclass
class Feedback:
    """What a coder learns from earlier tries: the last output of compiler and run, all diagnoses, and hints."""

    compile_output: str = ""
    run_output: str = ""
    diagnoses: list = field(default_factory=list)
    rewrite: bool = False
    stuck: bool = False

    def to_json(self) -> str:
        return json.dumps(asdict(self))


class Coder(Protocol):
    def generate(self, spec: FormatSpec, feedback: Feedback) -> str: ...


def strip_prose(text: str) -> str:
    """Source without a preamble, code fences or a closing remark; ValueError if there is none."""
    fenced = re.search(r"```(?:python)?\n(.*?)```", text, re.S)
    if fenced:
        text = fenced[1]
    lines = text.split("\n")
    start = next((i for i, x in enumerate(lines) if re.match(r"(import |from \w|def |class |@|#|\"\"\"|[A-Z_]+ = )", x)), None)
    if start is None:
        raise ValueError("the output holds no code")
    return "\n".join(lines[start:]).rstrip() + "\n"


class TemplateCoder:
    """A complete reader for one format: it parses column specifications when called, decodes all storage types, and
    imports nothing of this package.  Formats beyond the built-in ones bring their own text (see register_format)."""

    def generate(self, spec: FormatSpec, feedback: Feedback) -> str:
        return spec.template if spec.template else templates.source(spec.kind, spec.constants)


@dataclass(frozen=True)
class Fault:
    """Something put wrong in good source, by edits of which those apply whose text is there.  It is taken out again when an
    explanation, or the plain output of compiler or run, names its kind."""

    kind: str
    edits: tuple[tuple[str, str], ...] = ()


START = "    pages = np.asarray(pages, np.uint8).reshape(-1, PAGE)\n"
FAULTS = {
    "syntax": Fault("compile", ((START, START + "    def = pages\n"),)),
    "crash": Fault("run", ((START, START + "    raise IndexError('offset outside the page')\n"),)),
    "lost_rows": Fault("row_count", ((START, START + "    pages = pages[:-1] if len(pages) > 1 else pages[:0]\n"),)),
    "wrong_epoch": Fault("value", (("np.int64(10957)", "np.int64(10956)"), ("np.int32(10957)", "np.int32(10956)"), ("1970 * 12", "1971 * 12"))),
    "sign_lost": Fault("value", (("np.where(negative, -out, out)", "out"), ("raw[:, 0].astype(np.int8).astype(np.int64)", "raw[:, 0].astype(np.int64)"))),
    "null_bits_turned": Fault("null_count", (("(bit == 1)", "(bit == 0)"), ("(k % 8) & 1 == 0", "(k % 8) & 1 == 1"))),
    "scale_lost": Fault("value", (("4 * (weight - count + 1)", "4 * (weight - count)"), ("np.full(len(raw), -scale)", "np.full(len(raw), 0)"))),
    "prose": Fault("prose"),
}
#: Kinds that can show a wrong branch: it may give other values, other nulls, or no result at all.
SHOWN = {"value", "null_count", "run"}


class FaultyCoder:
    """Puts faults into good source, also into branches of types that a table doesn't have.  The first fault left is taken
    out when feedback shows it; a stubborn one only when the coder is told to write anew or that it is stuck."""

    def __init__(self, faults: tuple[str, ...] = (), stubborn: tuple[str, ...] = ()):
        self.faults, self.stubborn, self.inner = list(faults), set(stubborn), TemplateCoder()

    def generate(self, spec: FormatSpec, feedback: Feedback) -> str:
        said = {d["kind"] for d in feedback.diagnoses[-1:]} | ({"compile"} if feedback.compile_output else set()) | ({"run"} if feedback.run_output else set())
        if self.faults:
            first = self.faults[0]
            kind = FAULTS[first].kind
            shown = {kind} if kind in ("compile", "run", "row_count", "prose") else SHOWN
            if said & shown and (first not in self.stubborn or feedback.rewrite or feedback.stuck):
                self.faults.pop(0)
        source = self.inner.generate(spec, feedback)
        if not self.faults:
            return source
        if self.faults[0] == "prose":
            return "I could not write this reader.\n"
        for old, new in FAULTS[self.faults[0]].edits:
            source = source.replace(old, new)
        return source


def ask(command: list[str], request: dict, timeout: int) -> str:
    """What a command answers to a request that it gets as JSON on its input."""
    return subprocess.run(command, input=json.dumps(request), capture_output=True, text=True, timeout=timeout, check=True).stdout


class ExternalCoder:
    """Runs a command that gets specification and feedback as JSON on its input and answers with source."""

    def __init__(self, command: list[str], timeout: int = 600):
        self.command, self.timeout = command, timeout

    def generate(self, spec: FormatSpec, feedback: Feedback) -> str:
        return ask(self.command, {"spec": json.loads(spec.to_json()), "feedback": json.loads(feedback.to_json())}, self.timeout)
