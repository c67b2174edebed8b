"""Models behind one protocol: ``complete(request) -> (raw text, prompt tokens, reply tokens)``."""

from __future__ import annotations

import base64
import hashlib
import json
import time
import urllib.request
from dataclasses import dataclass, field, replace

from lmrel.functions.constraints import Constraint
from lmrel.functions.prompts import SEPARATOR, approx_tokens
from lmrel.functions.skills import BY_QUESTION


@dataclass(frozen=True)
class Request:
    question: str
    inputs: str  # the row's fields as JSON
    prompt: str
    constraint: Constraint
    modality: str = "text"
    batch: tuple[str, ...] | None = None  # the rows of a prompt for several
    media: tuple[tuple[str, bytes], ...] = ()  # (kind, bytes) of the references among the inputs


def said(value: object, ddl: str) -> str:
    """A value as a model would write it."""
    if value is None:
        return ""
    return json.dumps(value, ensure_ascii=False) if ddl.startswith(("array", "struct")) or isinstance(value, bool) else str(value)


@dataclass
class RuleProvider:
    """Answers registered questions by rule; ``service_s`` is a simulated service time."""

    name: str = "rule"
    service_s: float = 0.0

    def answer(self, r: Request) -> object:
        skill = BY_QUESTION.get(r.question)
        if skill is None:
            raise KeyError(f"the rule reasoner does not know: {r.question}")
        return skill.rule(*json.loads(r.inputs).values())

    def raw(self, r: Request) -> str:
        return said(self.answer(r), r.constraint.ddl)

    def complete(self, r: Request) -> tuple[str, int, int]:
        if self.service_s:
            time.sleep(self.service_s)
        raw = f"{SEPARATOR} ".join(self.raw(replace(r, inputs=x, batch=None)) for x in r.batch) if r.batch else self.raw(r)
        return raw, approx_tokens(r.prompt), approx_tokens(raw)


@dataclass
class NoisyProvider(RuleProvider):
    """Wrong with probability ``error``, malformed with probability ``malformed``, seeded by the input.

    Constraints repair malformed replies only; both rates can differ by modality.
    """

    error: dict = field(default_factory=lambda: {"text": 0.05})
    malformed: float = 0.0

    @staticmethod
    def draw(name: str, question: str, inputs: str) -> float:
        return int(hashlib.md5(f"{name}|{question}|{inputs}".encode()).hexdigest()[:8], 16) / 2**32

    def raw(self, r: Request) -> str:
        value, u = self.answer(r), self.draw(self.name, r.question, r.inputs)
        e = self.error.get(r.modality, self.error.get("text", 0.0))
        if u < e:
            options = r.constraint.options
            value = (not value) if isinstance(value, bool) else value + 1 if isinstance(value, (int, float)) else options[(options.index(value) + 1) % len(options)] if options and value in options else "unknown"
        raw = said(value, r.constraint.ddl)
        if e <= u < e + self.malformed:
            raw = f"Well, I would say it is: {raw}!!"
        return raw


#: Ours; only their order (audio worst, the larger model better) mirrors published behaviour.
PROFILES = {
    "small-2b": NoisyProvider("small-2b", 0.0, {"text": 0.08, "image": 0.16, "audio": 0.24}, 0.10),
    "small-4b": NoisyProvider("small-4b", 0.0, {"text": 0.05, "image": 0.12, "audio": 0.20}, 0.08),
    "dense-4b": NoisyProvider("dense-4b", 0.0, {"text": 0.06, "image": 0.13, "audio": 0.22}, 0.08),
    "dense-12b": NoisyProvider("dense-12b", 0.0, {"text": 0.03, "image": 0.10, "audio": 0.18}, 0.05),
    "hosted": NoisyProvider("hosted", 0.0, {"text": 0.04, "image": 0.09, "audio": 0.10}, 0.03),
}


@dataclass
class ReplayProvider:
    """Answers recorded earlier, by question and inputs; anything else raises."""

    answers: dict
    name: str = "replay"

    def complete(self, r: Request) -> tuple[str, int, int]:
        raw = self.answers[(r.question, r.inputs)]
        return raw, approx_tokens(r.prompt), approx_tokens(raw)


@dataclass
class HttpProvider:
    """A chat endpoint in the widely used JSON form; grammar hints go along, usage comes back."""

    base_url: str
    model: str
    api_key: str | None = None
    timeout: float = 60.0
    max_len: int = 32_000
    name: str = "http"

    def complete(self, r: Request) -> tuple[str, int, int]:
        if approx_tokens(r.prompt) > self.max_len:
            raise ValueError("the prompt is longer than the model's window")
        files = [{"type": f"{kind}_url", f"{kind}_url": {"url": f"data:{kind}/*;base64,{base64.b64encode(own).decode()}"}} for kind, own in r.media]
        content = [*files, {"type": "text", "text": r.prompt}] if files else r.prompt
        body = {"model": self.model, "temperature": 0, "messages": [{"role": "user", "content": content}]}
        if pattern := r.constraint.regex():
            body["guided_regex"] = pattern
        headers = {"Content-Type": "application/json"} | ({"Authorization": f"Bearer {self.api_key}"} if self.api_key else {})
        request = urllib.request.Request(f"{self.base_url}/chat/completions", json.dumps(body).encode(), headers)
        with urllib.request.urlopen(request, timeout=self.timeout) as reply:
            got = json.load(reply)
        raw, usage = got["choices"][0]["message"]["content"], got.get("usage", {})
        return raw, usage.get("prompt_tokens", approx_tokens(r.prompt)), usage.get("completion_tokens", approx_tokens(raw))
