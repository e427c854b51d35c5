"""The whole detector on a bounded context: fit, select, score."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd

from vtask.kernels import selection as sel
from vtask.kernels.backbones import make, support
from vtask.kernels.draws import rng, uniforms
from vtask.kernels.table import Frame, Schema
from vtask.kernels.tasks import TEMPLATES, Spec, Task, grid


@dataclass(frozen=True)
class Config:
    backbone: str = "kernel"
    splits: int = 3
    rho_h: float = 0.10
    gamma: float = 0.70
    w_auc: float = 1.5
    retention: str = "all"
    ensemble: str = "low2mean"
    ties: str = "strict"
    seed: int = 0
    context: int = 2000  # rows of the context that a fitted detector holds
    templates: str = "SLGPD"
    intra: str = "adaptive"  # or 'default'
    inter: str = "adaptive"  # or 'random<k>'


def with_(cfg: Config, **changes) -> Config:
    return replace(cfg, **changes)


def replace_seed(cfg: Config, seed: int) -> Config:
    return replace(cfg, seed=seed)


def full(cfg: Config) -> Config:
    """With all templates, so that supports can be shared by every choice among them."""
    return replace(cfg, templates="SLGPD")


@dataclass
class Evaluation:
    """Supports of every candidate: what selection, ablations and calibration share."""

    frame: Frame
    schema: Schema
    tasks: dict[str, Task]
    stats: list[sel.Stats]
    nominal: dict[str, np.ndarray]
    calls: int = 0
    rows: int = 0


def evaluate(context: pd.DataFrame, attrs: list[str], cfg: Config) -> Evaluation:
    """Supports of held-out rows and probes for each candidate, labels frozen from the whole context.

    Of a context of more than cfg.context rows those of smallest draw count: by
    name where rows have one, so that every mode takes the same.
    """
    if len(context) > cfg.context:
        by = np.lexsort((context["rid"], uniforms(0, "ctx", context["rid"]))) if "rid" in context else rng(cfg.seed, "context").permutation(len(context))
        context = context.iloc[by[: cfg.context]]
    schema = Schema.fit(context, attrs)
    f = schema.frame(context)
    schema.profile  # noqa: B018  raises where no attribute is usable
    held = sel.folds(f.n, cfg.splits, cfg.rho_h, cfg.seed)
    sets = []
    for s, rows in enumerate(held):
        rest = np.setdiff1d(np.arange(f.n), rows)
        train, nom = f.take(rest), f.take(rows)
        sets.append((rest, rows, train, nom, sel.probes(nom, train, cfg.seed, s)[0]))
    ev = Evaluation(f, schema, {}, [], {})
    for task, specs in grid(f, schema).items():
        if task[0] not in cfg.templates:
            continue
        seen = set()
        for spec in specs if cfg.intra == "adaptive" else specs[: max(1, _default(specs))][-1:]:
            t = Task.fit(spec, f, cfg.seed)
            y = t.label(f)
            if np.unique(y).size < 2 or y.tobytes() in seen:
                continue  # degenerate, or the same labels as another candidate's
            seen.add(y.tobytes())
            nom, vio = [], []
            for rest, rows, train, h, broken in sets:
                b = make(cfg.backbone).fit(t.predictors(train), y[rest])
                nom.append(support(b, t.predictors(h), y[rows]))
                vio.append(support(b, t.predictors(broken), t.label(broken)))
                ev.calls, ev.rows = ev.calls + 1, ev.rows + h.n + broken.n
            ev.tasks[spec.name], ev.nominal[spec.name] = t, np.concatenate(nom)
            ev.stats.append(sel.candidate_stats(task, spec.name, ev.nominal[spec.name], np.concatenate(vio), cfg.ties))
    return ev


def _default(specs: list[Spec]) -> int:
    """Position of the shared default: robust, two bins, two clusters, two token bins, first target."""
    return next((i + 1 for i, s in enumerate(specs) if s.transform == "robust" and s.bins == 2 and s.clusters == 2 and s.token_bins == 2), 1)


def choose(ev: Evaluation, cfg: Config) -> list[sel.Stats]:
    """Representatives of the tasks, then the tasks to keep; works on cached supports."""
    stats = [s for s in ev.stats if s.task[0] in cfg.templates]
    tasks = sorted({s.task for s in stats}, key=lambda t: (TEMPLATES.index(t[0]), t))
    reps = [sel.intra([s for s in stats if s.task == t], share=cfg.gamma) for t in tasks]
    if not reps:
        return []
    if cfg.inter.startswith("random"):
        k = int(cfg.inter[6:])
        return [reps[i] for i in sorted(rng(cfg.seed, f"retain.{k}").permutation(len(reps))[:k])]
    return sel.inter(reps, cfg.retention, cfg.w_auc)


@dataclass
class Fitted:
    """Kept tasks with their backbones and calibration levels; bounded by the context's size, so it can be broadcast."""

    cfg: Config
    attrs: list[str]
    schema: Schema
    kept: list[sel.Stats]
    tasks: list[Task]
    backbones: list
    levels: list[np.ndarray]
    counters: dict = field(default_factory=dict)

    def score_tasks(self, pdf: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
        """(supports, surprisals), a column a kept task."""
        f = self.schema.frame(pdf)
        k = np.stack([support(b, t.predictors(f), t.label(f)) for t, b in zip(self.tasks, self.backbones, strict=True)], axis=1)
        return k, np.stack([sel.surprisal(k[:, j], v) for j, v in enumerate(self.levels)], axis=1)

    def score(self, pdf: pd.DataFrame, how: str | None = None) -> np.ndarray:
        if not self.tasks:
            return np.full(len(pdf), np.nan)
        return sel.combine(self.score_tasks(pdf)[1], self.kept, how or self.cfg.ensemble, self.cfg.w_auc)


def finish(ev: Evaluation, cfg: Config, attrs: list[str]) -> Fitted:
    kept = choose(ev, cfg)
    tasks = [ev.tasks[s.name] for s in kept]
    backs = [make(cfg.backbone).fit(t.predictors(ev.frame), t.label(ev.frame)) for t in tasks]
    return Fitted(cfg, attrs, ev.schema, kept, tasks, backs, [np.sort(ev.nominal[s.name]) for s in kept], {"fit_calls": ev.calls, "fit_rows": ev.rows})


def fit(context: pd.DataFrame, attrs: list[str], cfg: Config | None = None) -> Fitted:
    cfg = cfg or Config()
    return finish(evaluate(context, attrs, cfg), cfg, attrs)
