"""A small language of learning tasks.

    [name =] RUN task ON source [HAVING TIME 1h30m, EPSILON 0.01, MAX_ITER 100]
             [USING ALGORITHM sgd, CONVERGENCE l2(), STEP 1, SAMPLER shuffle()];
    PERSIST name ON 'path';
    result = PREDICT ON source WITH name;
    EXPLAIN RUN ...

A source is a table, a quoted path, ``libsvm(path)``, or ``file:label, file:from-to`` with columns counted from 1.
Words of the language may be in any case. Errors tell the position.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from ..functions.gradients import TASKS
from ..functions.steps import NORMS

_TOKEN = re.compile(r"\s*(?:('[^']*')|([A-Za-z_./][\w./*-]*)|(\d[\w.]*(?:[eE][+-]?\d+)?)|([=,;:()\-]))")
_DURATION = re.compile(r"(?:(\d+)h)?(?:(\d+)m)?(?:(\d+)s)?$")


class LanguageError(ValueError):
    pass


@dataclass
class Source:
    path: str
    format: str = "table"
    label: int | None = None
    features: tuple[int, int] | None = None


@dataclass
class Statement:
    kind: str
    name: str | None = None
    task: str | None = None
    source: Source | None = None
    having: dict = field(default_factory=dict)
    using: dict = field(default_factory=dict)
    path: str | None = None
    model: str | None = None
    explain: bool = False


def seconds(text: str) -> int:
    """Of a duration as 1h30m, 2m or 90s."""
    m = _DURATION.match(text)
    if not m or not any(m.groups()):
        raise LanguageError(f"bad duration {text}")
    h, mi, s = (int(x or 0) for x in m.groups())
    return 3600 * h + 60 * mi + s


class Parser:
    def __init__(self, text: str):
        self.tokens, at = [], 0
        while text[at:].strip():
            m = _TOKEN.match(text, at)
            if not m:
                raise LanguageError(f"unreadable text at {at}: {text[at:at + 10]!r}")
            self.tokens.append((m[0].strip(), m.start() + len(m[0]) - len(m[0].lstrip())))
            at = m.end()
        self.k = 0

    def peek(self) -> str:
        return self.tokens[self.k][0] if self.k < len(self.tokens) else ""

    def fail(self, what: str):
        where = self.tokens[self.k][1] if self.k < len(self.tokens) else "the end"
        raise LanguageError(f"{what} at {where}, found {self.peek()!r}")

    def take(self, *words: str) -> str:
        t = self.peek()
        if not t or words and t.upper() not in words:
            self.fail(f"expected {' or '.join(words) or 'a word'}")
        self.k += 1
        return t

    def accept(self, word: str) -> bool:
        if self.peek().upper() == word:
            self.k += 1
            return True
        return False

    def statements(self) -> list[Statement]:
        out = []
        while self.peek():
            if self.accept(";"):
                continue
            out.append(self.statement())
            if self.peek():
                self.take(";")
        return out

    def statement(self) -> Statement:
        name = None
        if self.k + 1 < len(self.tokens) and self.tokens[self.k + 1][0] == "=":
            name = self.take()
            self.take("=")
        explain = self.accept("EXPLAIN")
        word = self.take("RUN", "PERSIST", "PREDICT").upper()
        if word == "PERSIST":
            model = self.take()
            self.take("ON")
            return Statement("persist", model=model, path=self.take().strip("'"))
        if word == "PREDICT":
            self.take("ON")
            source = self.source()
            self.take("WITH")
            return Statement("predict", name, source=source, model=self.take().strip("'"))
        task = self.take().lower()
        if self.accept("("):
            self.take(")")
        if task not in TASKS:
            raise LanguageError(f"unknown task {task}")
        self.take("ON")
        s = Statement("run", name, task, self.source(), explain=explain)
        while self.peek().upper() in ("HAVING", "USING"):
            which = self.take().upper()
            items = s.having if which == "HAVING" else s.using
            if items:
                self.fail(f"second {which}")
            self.items(which, items)
        if s.using.get("algorithm") == "bgd" and "sampler" in s.using:
            raise LanguageError("SAMPLER: batch descent takes no sample")
        return s

    def source(self) -> Source:
        word = self.take().strip("'")
        if word.lower() == "libsvm" and self.accept("("):
            path = self.take().strip("'")
            self.take(")")
            return Source(path, "libsvm")
        if not self.accept(":"):
            return Source(word, "table" if re.fullmatch(r"\w+", word) else "csv")
        label = self.number(int)
        src = Source(word, "csv", label)
        if self.accept(","):
            if self.take().strip("'") != word:
                self.fail("expected the same file")
            self.take(":")
            lo = self.number(int)
            hi = self.number(int) if self.accept("-") else lo
            if lo < 1 or hi < lo:
                self.fail(f"bad range {lo}-{hi}")
            src.features = (lo, hi)
        return src

    def number(self, kind):
        negative = self.accept("-")
        text = self.take()
        try:
            return kind(text) * (-1 if negative else 1)
        except ValueError:
            self.k -= 1
            self.fail("expected a number")

    def items(self, which: str, out: dict) -> None:
        known = ("TIME", "EPSILON", "MAX_ITER") if which == "HAVING" else ("ALGORITHM", "CONVERGENCE", "STEP", "SAMPLER", "TRANSFORM", "BATCH")
        while True:
            key = self.take(*known).lower()
            if key in out:
                self.k -= 1
                self.fail(f"second {key.upper()}")
            if key == "time":
                out[key] = seconds(self.take())
            elif key in ("epsilon", "step"):
                out[key] = self.number(float)
            elif key in ("max_iter", "batch"):
                out[key] = self.number(int)
            else:
                out[key] = self.take().lower()
                if self.accept("("):
                    self.take(")")
            if key in ("epsilon", "max_iter", "step", "batch") and out[key] <= 0:
                self.fail(f"{key.upper()} must be positive")
            if not self.accept(","):
                return


def parse(text: str) -> list[Statement]:
    return Parser(text).statements()


class Session:
    """Executes statements over given tables; names of results live in the session."""

    def __init__(self, spark, sf_dir: str):
        self.spark, self.sf_dir, self.names, self.models = spark, sf_dir, {}, {}

    def request(self, s: Statement):
        from .optimizer import Request

        norm = s.using.get("convergence", "l1")
        if norm not in NORMS:
            raise LanguageError(f"CONVERGENCE: unknown {norm}")
        return Request(TASKS[s.task], s.having.get("epsilon", 1e-3), s.having.get("max_iter"), s.having.get("time"), s.using.get("algorithm"), s.using.get("sampler"), s.using.get("transform"), s.using.get("step", 1.0), norm=norm, batch=s.using.get("batch", 1000), epsilon_given="epsilon" in s.having, fixed_iterations="max_iter" in s.having and "epsilon" not in s.having)

    def units(self, src: Source):
        """(raw rows, transform)."""
        from ..sources import tasks

        if src.format == "libsvm":
            raw = tasks.densify(tasks.read_libsvm_units(self.spark, src.path))
            return raw, lambda df: df
        if src.format == "csv":
            import pyspark.sql.functions as F

            cells = F.transform(F.split(F.trim("value"), ","), lambda x: x.cast("double"))
            lo, hi = src.features or (1, 0)
            label = (src.label or 1) if src.features else (src.label or 1)
            picked = F.slice(cells, lo, hi - lo + 1) if src.features else F.concat(F.slice(cells, 1, label - 1), F.slice(cells, label + 1, 1 << 20))
            raw = tasks.numbered_lines(self.spark, src.path)
            return raw, lambda df: df.select("unit_id", F.element_at(cells, label).alias("label"), picked.alias("features"), *([c for c in df.columns if c == "part_id"]))
        if src.path in tasks.TASKS:
            task = tasks.TASKS[src.path]
            raw = tasks.table(self.spark, self.sf_dir, task.table)
            if task.unit_id != "unit_id":
                raw = raw.selectExpr("*", f"{task.unit_id} AS unit_id")
            return raw, lambda df: tasks.transform_columns(df, "unit_id", task.label, task.features)
        raise LanguageError(f"no source {src.path}")

    def execute(self, text: str) -> dict:
        from ..sources.models import load_model, save_model
        from .cost import Env, place_operators
        from .optimizer import execute, optimise, predictions

        for s in parse(text):
            if s.kind == "persist":
                save_model(self.spark, self.models[s.model], s.path)
                continue
            raw, transform = self.units(s.source)
            if s.kind == "predict":
                m = self.models.get(s.model) or load_model(self.spark, s.model)
                self.names[s.name or "result"] = predictions(transform(raw), m["weights"], m["gradient"])
                continue
            req = self.request(s)
            report = optimise(transform(raw), req)
            place = place_operators(report.data, req.batch, Env(), report.chosen.algorithm != "bgd")["transform"]
            if s.explain:
                self.names[s.name or "plan"] = report.frame(self.spark)
                continue
            # placed by the size that the plan was costed with: on the driver where one partition holds all units
            fit = execute(report.chosen, raw, transform, req, data=report.data)
            self.models[s.name or "model"] = {"task": s.task, "gradient": req.gradient, "weights": fit.weights, "plan": report.chosen.key, "tolerance": req.epsilon, "norm": req.norm, "iters": fit.iterations, "status": fit.status, "place": place}
        return self.names


def run_sql(spark, sf_dir: str, script: str) -> dict:
    return Session(spark, sf_dir).execute(script)
