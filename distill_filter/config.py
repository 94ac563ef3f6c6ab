"""Settings of specs, teachers, students and runs. Defaults are ours; published runs do not print theirs."""

from __future__ import annotations

from dataclasses import dataclass, replace


@dataclass(frozen=True)
class FilterSpec:
    """A filter: what passes, by a rule that stands in for a costly annotator. Names of rules: see operators.teacher."""

    name: str
    prompt_text: str
    minority_class: int = 1


SPECS = {
    s.name: s
    for s in (
        FilterSpec("topic_hostile", "Pass texts that hold an insult from the lexicon."),
        FilterSpec("topic_legal", "Pass texts that state a licence or reserve rights."),
        FilterSpec("topic_private", "Pass texts that hold a token with a digit."),
        FilterSpec("mainstream", "Pass texts at least 30 % of whose tokens are common in the corpus.", 0),
        FilterSpec("quality", "Pass texts that are not symbol runs, shouting, table debris or repetition.", 0),
    )
}


@dataclass(frozen=True)
class TeacherConfig:
    """mode: exact, noisy (verdicts flip with probability eps_*), or graded (pass probability by evidence)."""

    teacher_id: str = "teacher"
    mode: str = "exact"
    eps_pos: float = 0.0
    eps_neg: float = 0.0

    def noisy(self, eps: float) -> TeacherConfig:
        return replace(self, mode="noisy", eps_pos=eps, eps_neg=eps)


@dataclass(frozen=True)
class StudentConfig:
    """kind: logodds, focal, mllib or vector. smoothing, min_df and z_min are the log-odds student's; warm_start (an
    ablation) lets a focal student begin where the last round's ended; a log-odds one has no state to begin from."""

    kind: str = "logodds"
    smoothing: float = 0.5
    min_df: int = 2
    z_min: float = 2.0
    prior: bool = True
    focal_gamma: float = 2.0
    class_weight: bool = False
    epochs: int = 60
    rate: float = 0.5
    bits: int = 18
    warm_start: bool = False


@dataclass(frozen=True)
class RunConfig:
    """One distillation run.

    batch: labels bought each round; budget: labels in all. radius_scale 1 is the published radius; smaller values are
    for small inputs and are shown in every trace. policy: band, random, uncertainty, pool_uncertainty or pool_cut.
    unlabelled: implied, constant or labelled_only. nested: False takes both ends of each update as they are; True only
    narrows. on_exhausted: stop or wrap; on_single_class: prior or grow_seed. cut of the final student: half, eot, balanced, or a pass share.
    """

    width: int = 64
    seed: int = 7
    batch: int = 512
    budget: int = 1536
    delta: float = 0.1
    radius_scale: float = 1.0
    unlabelled: str = "implied"
    nested: bool = False
    radius: str = "bernstein"
    policy: str = "band"
    uncertainty_width: float = 0.4
    budget_mode: str = "total"
    on_exhausted: str = "stop"
    on_single_class: str = "prior"
    cut: str | float = "half"

    @property
    def rounds(self) -> int:
        return self.budget // self.batch - (self.budget_mode == "total")
