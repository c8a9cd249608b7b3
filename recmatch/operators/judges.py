"""Judges: what answers the three questions. The formulas are SQL text that Spark and the oracles read alike."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class NoProbabilities(ValueError):
    """The judge gives labels only."""


def unit(text: str, name: str) -> str:
    """A number in [0, 1) from a digest of SQL text."""
    if name == "spark":
        return f"cast(conv(substr(md5({text}), 1, 8), 16, 10) as double) / 4294967296"
    return f"cast(cast(('0x' || substr(md5({text}), 1, 8)) as bigint) as double) / 4294967296"


@dataclass(frozen=True)
class Judge:
    """A judge on similarities.

    p(yes) = 1 / (1 + exp(-beta (sim - tau))); of two, p(first) uses their difference plus delta, a liking for what
    comes first; of a list, the largest sim less lam for each place; below theta the opt-out. The sigmas add noise
    from a digest of seed, question and ids to sim, as weaker models err more. sigma_triple errs anew in each comparison;
    sigma_record misreads a candidate the same way in all comparisons of its list, so that more of them do not average it out.
    """

    name: str = "expression"
    beta: float = 12.0
    tau: float = 0.9
    delta: float = 0.0
    lam: float = 0.0
    theta: float | None = None
    sigma_pair: float = 0.0
    sigma_triple: float = 0.0
    sigma_list: float = 0.0
    sigma_record: float = 0.0
    seed: int = 1
    has_probs: bool = True
    deterministic: bool = True

    @property
    def least(self) -> float:
        return self.tau if self.theta is None else self.theta

    def with_tau(self, tau: float) -> Judge:
        return replace(self, tau=tau)

    def _noisy(self, sim: str, sigma: float, kind: str, ids: str, name: str) -> str:
        if not sigma:
            return sim
        key = f"concat('{self.seed}{kind}', {ids})"
        return f"({sim} + {sigma}e0 * ({unit(key, name)} - 0.5e0))"

    def p_yes(self, name: str, sim: str = "sim", a: str = "anchor_id", c: str = "cand_id") -> str:
        ids = f"cast({a} as {_text(name)}), '|', cast({c} as {_text(name)})"
        s = self._noisy(sim, self.sigma_pair, "|p|", ids, name)
        return f"round(1 / (1 + exp(-{self.beta}e0 * ({s} - {self.tau}e0))), 6)"

    def p_first(self, name: str, x: str, y: str, xi: str, yi: str, a: str = "anchor_id") -> str:
        ids = f"cast({a} as {_text(name)}), '|', cast({xi} as {_text(name)}), '|', cast({yi} as {_text(name)})"
        read = lambda v, i: self._noisy(v, self.sigma_record, "|r|", f"cast({a} as {_text(name)}), '|', cast({i} as {_text(name)})", name)
        s = self._noisy(f"{read(x, xi)} - {read(y, yi)}", self.sigma_triple, "|t|", ids, name)
        return f"round(1 / (1 + exp(-{self.beta}e0 * ({s} + {self.delta}e0))), 6)"

    def worth(self, name: str, sim: str = "sim", pos: str = "pos", a: str = "anchor_id", c: str = "cand_id") -> str:
        ids = f"cast({a} as {_text(name)}), '|', cast({c} as {_text(name)})"
        s = self._noisy(sim, self.sigma_list, "|l|", ids, name)
        return f"round({s} - {self.lam}e0 * {pos}, 6)"

    def held(self, name: str, sim: str = "sim", a: str = "anchor_id", c: str = "cand_id") -> str:
        """What the opt-out looks at: the similarity without place."""
        return self.worth(name, sim, "0", a, c)


def _text(name: str) -> str:
    return "string" if name == "spark" else "varchar"


def black_box(judge: Judge) -> Judge:
    return replace(judge, name=f"{judge.name} black box", has_probs=False)


LENIENT, DEFAULT, STRICT = Judge("lenient", tau=0.8), Judge("default"), Judge("strict", tau=0.92)
#: A ladder of judges from small to large: noise falls; the small ones misread more when comparing.
LADDER = tuple(Judge(f"size {i}", tau=0.85, sigma_pair=s, sigma_record=1.6 * s, sigma_list=1.3 * s, seed=i) for i, s in enumerate((0.8, 0.6, 0.45, 0.3, 0.2, 0.12, 0.06, 0.0), 1))
#: Two strong judges for the main table: an older, noisier one and a newer one.
OLDER, NEWER = Judge("older", tau=0.8, sigma_pair=0.25, sigma_triple=0.25, sigma_list=0.1, lam=0.01, seed=11), Judge("newer", tau=0.85, sigma_pair=0.12, sigma_triple=0.1, sigma_list=0.05, lam=0.005, seed=12)
RANKER = Judge("ranker", tau=0.85, sigma_pair=0.05, seed=13)


class ReplayJudge:
    """Answers from a call log (prompt_hash, answer, p); a prompt that is not there gets null."""

    def __init__(self, log: DataFrame):
        self.log = log.select("prompt_hash", "answer", "p").dropDuplicates(["prompt_hash"])

    def ask(self, prompts: DataFrame) -> DataFrame:
        return prompts.withColumn("prompt_hash", F.sha2("prompt", 256)).join(self.log, "prompt_hash", "left")


class RemoteJudge:
    """Asks each distinct prompt once through a transport, a function of a list of prompts to (answer, p) pairs.

    Partitions bound the calls in flight. The log is a table by prompt hash; replaying it costs no calls.
    """

    def __init__(self, transport, in_flight: int = 8, batch: int = 32, retries: int = 2):
        self.transport, self.in_flight, self.batch, self.retries = transport, in_flight, batch, retries

    def log(self, prompts: DataFrame, known: DataFrame | None = None) -> DataFrame:
        asked = prompts.select("prompt").distinct().withColumn("prompt_hash", F.sha2("prompt", 256))
        if known is not None:
            asked = asked.join(known.select("prompt_hash"), "prompt_hash", "left_anti")
        transport, batch, retries = self.transport, self.batch, self.retries

        def run(frames):
            for f in frames:
                answers, ps = [], []
                for i in range(0, len(f), batch):
                    for left in range(retries, -1, -1):
                        try:
                            got = transport(f["prompt"].iloc[i : i + batch].tolist())
                            break
                        except OSError:
                            if not left:
                                raise
                    answers += [a for a, _ in got]
                    ps += [p for _, p in got]
                yield f.assign(answer=answers, p=ps)[["prompt_hash", "prompt", "answer", "p"]]

        return asked.repartition(self.in_flight, "prompt_hash").mapInPandas(run, "prompt_hash string, prompt string, answer string, p double")


def prompt_hash(prompt: str) -> str:
    return hashlib.sha256(prompt.encode()).hexdigest()
