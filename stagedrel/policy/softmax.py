"""A small policy with exact log-probabilities, factored as the reasoning steps are.

Heads: style of the writing, relevance, object type, entity type, and a label among those that the types allow. A
response is written out of the outcomes, so rewards read text. Code here runs in Python workers and is pickled by
value.
"""

from __future__ import annotations

import sys

import numpy as np
from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])

TYPES = ("per", "org", "loc", "misc")
STYLES = ("long", "short", "malformed")
WIDTH = 37
HEADS = {"style": len(STYLES), "relevance": 2, "obj": len(TYPES), "ent": len(TYPES)}


class Policy:
    """theta: a row of weights for each outcome of each head, then a row for each real label."""

    def __init__(self, labels, theta=None, flat: bool = False):
        """labels: (label, obj_type, ent_type) of real relations, in order; flat: one head over all labels and none."""
        self.labels, self.flat = list(labels), flat
        self.names = [x[0] for x in self.labels]
        self.heads, at = {}, 0
        sizes = HEADS | {"label": len(self.labels)} if not flat else {"style": len(STYLES), "flat": len(self.labels) + 1}
        for name, n in sizes.items():
            self.heads[name] = slice(at, at + n)
            at += n
        self.rows = at
        self.theta = np.zeros((at, WIDTH)) if theta is None else np.asarray(theta, float).reshape(at, WIDTH)
        self.allowed = np.zeros((len(TYPES), len(TYPES), len(self.labels)), bool)
        for k, (_, o, e) in enumerate(self.labels):
            self.allowed[TYPES.index(o), TYPES.index(e), k] = True

    def copy(self) -> Policy:
        return Policy(self.labels, self.theta.copy(), self.flat)

    def with_label(self, label: str, obj: str, ent: str) -> Policy:
        """A label more is a row more: it starts as the mean of the labels with its relation's name, else of its types, else at 0."""
        kin = [k for k, (x, _, _) in enumerate(self.labels) if x.rsplit("/", 1)[1] == label.rsplit("/", 1)[1]] or [k for k, (_, o, e) in enumerate(self.labels) if (o, e) == (obj, ent)]
        rows = self.theta[self.heads["label"]]
        new = rows[kin].mean(axis=0) if kin else np.zeros(WIDTH)
        return Policy([*self.labels, (label, obj, ent)], np.concatenate([self.theta, new[None]]))

    def scores(self, x, head: str):
        return x @ self.theta[self.heads[head]].T

    def log_probs(self, x, head: str, mask=None):
        s = self.scores(x, head)
        if mask is not None:
            s = np.where(mask, s, -np.inf)
        top = np.max(s, axis=1, keepdims=True)
        top = np.where(np.isfinite(top), top, 0)
        with np.errstate(divide="ignore"):
            return s - top - np.log(np.maximum(np.exp(s - top).sum(axis=1, keepdims=True), 1e-300))

    def steps(self, x, choose):
        """Goes through the heads; choose(head, log_probs, active) gives the outcome of each row. Returns outcomes (-1: not taken) and log-probs."""
        n = len(x)
        taken, total = {}, np.zeros(n)
        for name in self.heads:
            mask, active = None, np.ones(n, bool)
            if name == "label":
                mask = self.allowed[taken["obj"], taken["ent"]]
                active = (taken["relevance"] == 1) & mask.any(axis=1)
            lp = self.log_probs(x, name, mask)
            pick = np.where(active, choose(name, lp, active), -1)
            taken[name] = pick
            total += np.where(active, lp[np.arange(n), np.maximum(pick, 0)], 0.0)
        return taken, total

    def replay(self, x, outcomes):
        """Log-probability of given outcomes."""
        return self.steps(x, lambda name, lp, active: np.where(active, outcomes[name], 0))[1]

    def gradient(self, x, outcomes, weight):
        """Sum over rows of weight times the gradient of the outcomes' log-probability. Outcomes of -1 don't count."""
        out = np.zeros_like(self.theta)
        for name, span in self.heads.items():
            k = np.asarray(outcomes[name])
            on = k >= 0
            if not on.any():
                continue
            mask = self.allowed[np.asarray(outcomes["obj"])[on], np.asarray(outcomes["ent"])[on]] if name == "label" else None
            p = np.exp(self.log_probs(x[on], name, mask))
            p = -p
            p[np.arange(on.sum()), k[on]] += 1
            out[span] += (p * weight[on, None]).T @ x[on]
        return out

    def answer(self, outcomes):
        if self.flat:
            return [self.names[k - 1] if k > 0 else "none" for k in outcomes["flat"]]
        return [self.names[k] if k >= 0 else "none" for k in outcomes["label"]]


def sampler(temperature: float, uniforms):
    """Choice of outcomes: the best at temperature 0 (the lowest number on ties), else by inverse distribution."""

    def choose(name, lp, active):
        if temperature == 0:
            return np.argmax(lp, axis=1)
        with np.errstate(invalid="ignore"):
            s = lp / temperature
        s = np.where(np.isfinite(s), s, -np.inf)
        top = np.max(s, axis=1, keepdims=True)
        p = np.exp(s - np.where(np.isfinite(top), top, 0))
        c = np.cumsum(p, axis=1)
        return np.minimum((c < uniforms[name][:, None] * c[:, -1:]).sum(axis=1), lp.shape[1] - 1)

    return choose


def render(policy: Policy, outcomes, k: int) -> str:
    """The response of row k."""
    style = STYLES[outcomes["style"][k]]
    answer = policy.answer({n: v[k : k + 1] for n, v in outcomes.items()})[0]
    if policy.flat:
        return f"<answer>{answer}</answer>"
    o, e = TYPES[outcomes["obj"][k]], TYPES[outcomes["ent"][k]]
    filler = " The scene is looked at from edge to edge before anything is said about it." * (14 if style == "long" else 0)
    lines = [
        f"Step 1: an object stands out in the picture.{filler}",
        "Step 2: text and object " + ("belong together." if outcomes["relevance"][k] else "have nothing in common."),
        "Step 3: the words are set against the picture.",
        f"Step 4: the object is of type {o} and the entity of type {e}.",
        "Step 5: only what these types allow is left.",
        f"Step 6: the choice is {answer}.",
    ]
    if style == "malformed":
        lines = lines[1:]
    return "<think>" + "\n".join(lines) + "\n</think>" + f"<answer>{answer}</answer>"


def trigram_counts(texts, width: int = 16):
    """Shares of hashed trigrams of bytes; width is a power of two."""
    out, bits = np.zeros((len(texts), width)), width.bit_length() - 1
    for k, t in enumerate(texts):
        r = np.frombuffer((t or "").lower().encode("utf-8", "replace"), np.uint8).astype(np.uint32)
        if len(r) > 2:
            h = (r[:-2] * np.uint32(65_599) + r[1:-1]) * np.uint32(65_599) + r[2:]
            out[k] = np.bincount((h * np.uint32(2_654_435_761)) >> np.uint32(32 - bits), minlength=width) / len(h)
    return out


def feature_batches(batches):
    """sample_id, gold, types, split and x: pooled image and crop, trigram shares of the text, and 1."""
    import pandas as pd

    for b in batches:
        x = np.concatenate([np.stack(b["pooled"].to_numpy()) * 10 if len(b) else np.zeros((0, 20)), trigram_counts(b["text"].tolist()) * 4, np.ones((len(b), 1))], axis=1)
        yield pd.DataFrame({"sample_id": b["sample_id"], "gold": b["gold"], "obj_type": b["obj_type"], "ent_type": b["ent_type"], "split": b["split"], "x": list(x)})


def targets(policy: Policy, gold, obj, ent, style=None, related=None):
    """Outcomes that a response with these parts has; style and relevance by default those of a long one that follows the label."""
    n = len(gold)
    index = {x: k for k, x in enumerate(policy.names)}
    label = np.array([index.get(g, -1) for g in gold])
    if policy.flat:
        return {"style": np.full(n, -1), "flat": label + 1}
    types = {t: k for k, t in enumerate(TYPES)}
    style = np.zeros(n, int) if style is None else np.asarray(style, int)
    related = (label >= 0).astype(int) if related is None else np.asarray(related, int)
    return {"style": style, "relevance": related, "obj": np.array([types.get(t, 0) for t in obj]), "ent": np.array([types.get(t, 0) for t in ent]), "label": label}


def uniforms_of(keys, heads):
    """Numbers in [0, 1) out of md5 over key and head: the same at every retry."""
    import hashlib

    return {h: np.array([int(hashlib.md5(f"{k}:{h}".encode()).hexdigest()[:13], 16) / 16**13 for k in keys]) for h in heads}


def _taught(policy: Policy, b):
    """(features, outcomes) of a batch of rows with gold, types and, where they were read from a response, style and relevance."""
    own = {c: b[c].to_numpy() for c in ("style", "related") if c in b}
    return np.stack(b["x"].to_numpy()), targets(policy, b["gold"], b["obj_type"], b["ent_type"], **own)


def sft_sums(policy: Policy, x, t):
    """Sums over rows of the gradient of the outcomes' log-probability, and of their negative log-probability."""
    on = {h: np.maximum(v, 0) for h, v in t.items()}
    loss = -sum(policy.log_probs(x, "flat")[np.arange(len(x)), t["flat"]]) if policy.flat else -policy.replay(x, on).sum()
    return policy.gradient(x, t, np.ones(len(x))), loss


class Adam:
    def __init__(self, m=0.0, v=0.0, t=0):
        self.m, self.v, self.t = m, v, t

    def step(self, g, lr):
        self.t += 1
        self.m, self.v = 0.9 * self.m + 0.1 * g, 0.999 * self.v + 0.001 * g * g
        return lr * (self.m / (1 - 0.9**self.t)) / (np.sqrt(self.v / (1 - 0.999**self.t)) + 1e-8)


def warmup_lr(step: int, total: int, base: float, ratio: float = 0.05) -> float:
    """Rises in a straight line over the first share of the steps, then stays."""
    ramp = max(1, int(total * ratio))
    return base * min(1.0, (step + 1) / ramp)


def sft_partial(policy: Policy):
    """Batches of features -> sums of the loss and its gradient, as (i, g) rows; i = -1 is the loss, -2 the count."""

    def run(batches):
        import pandas as pd

        total, loss, n = np.zeros_like(policy.theta), 0.0, 0
        for b in batches:
            if len(b):
                g, own = sft_sums(policy, *_taught(policy, b))
                total, loss, n = total + g, loss + own, n + len(b)
        if n:
            yield pd.DataFrame({"i": [*range(total.size), -1, -2], "g": [*total.ravel(), loss, float(n)]})

    return run


def sft_chain(policy: Policy, adam: Adam, batch: int, mask, total: int, lr: float, warmup: float):
    """Rows in the epoch's order -> the weights after an update for each batch, Adam's state, and the loss, as (i, g) rows in four parts."""

    def run(batches):
        import pandas as pd

        own, a, loss, n, held = policy.copy(), Adam(adam.m, adam.v, adam.t), 0.0, 0, None

        def update(rows):
            nonlocal loss, n
            g, part = sft_sums(own, *_taught(own, rows))
            loss, n = loss + part, n + len(rows)
            own.theta += a.step(g / len(rows), warmup_lr(a.t, total, lr, warmup)) * mask

        for b in batches:
            held = b if held is None else pd.concat([held, b], ignore_index=True)
            while len(held) >= batch:
                update(held.iloc[:batch])
                held = held.iloc[batch:].reset_index(drop=True)
        if held is not None and len(held):
            update(held)
        if n:
            size, full = own.theta.size, lambda x: np.broadcast_to(x, own.theta.shape).ravel()
            yield pd.DataFrame({"i": [*range(3 * size), -1, -2, -3], "g": [*own.theta.ravel(), *full(a.m), *full(a.v), loss, float(n), float(a.t)]})

    return run


def rollout_batches(policy: Policy, ref: Policy, k: int, temperature: float, seed: str):
    """A row per sample and response: outcomes, log-probabilities under the policy and the reference, text."""

    def run(batches):
        import pandas as pd

        for b in batches:
            if not len(b):
                continue
            x = np.repeat(np.stack(b["x"].to_numpy()), k, axis=0)
            ids, ks = np.repeat(b["sample_id"].to_numpy(), k), np.tile(np.arange(k), len(b))
            u = uniforms_of([f"{seed}:{i}:{j}" for i, j in zip(ids, ks, strict=True)], policy.heads) if temperature else {}
            taken, lp = policy.steps(x, sampler(temperature, u))
            yield pd.DataFrame({
                "sample_id": ids, "k": ks.astype("int64"), "gold": np.repeat(b["gold"].to_numpy(), k),
                "response": [render(policy, taken, j) for j in range(len(ids))], "lp_old": lp, "lp_ref": ref.replay(x, {h: np.maximum(v, 0) for h, v in taken.items()}),
                "outcomes": list(np.stack([taken[h] for h in policy.heads], axis=1)), "x": list(x),
            })

    return run


#: Columns that an update sums up beside its gradient, at i = -3 and below.
STATS = ("r_format", "r_length", "r_answer", "reward", "easy")


def update_sums(policy: Policy, x, outcomes, adv, lp_old, lp_ref, eps: float, beta: float):
    """Sums over responses of the clipped objective's gradient and of the objective."""
    lp = policy.replay(x, {h: np.maximum(v, 0) for h, v in outcomes.items()})
    log_x = np.clip(lp_ref - lp, -20, 20)
    ratio = np.exp(np.clip(lp - lp_old, -20, 20))
    held = ((adv > 0) & (ratio > 1 + eps)) | ((adv < 0) & (ratio < 1 - eps))
    gradient = policy.gradient(x, outcomes, np.where(held, 0, ratio * adv) - beta * (1 - np.exp(log_x)))
    return gradient, (np.minimum(ratio * adv, np.clip(ratio, 1 - eps, 1 + eps) * adv) - beta * (np.exp(log_x) - log_x - 1)).sum()


def update_partial(policy: Policy, eps: float, beta: float):
    """Batches of rollouts with advantages -> sums of the objective and its gradient, as (i, g) rows."""

    def run(batches):
        import pandas as pd

        total, value, n = np.zeros_like(policy.theta), 0.0, 0
        told = dict.fromkeys(STATS, 0.0)
        for b in batches:
            if len(b):
                told = {c: told[c] + float(b[c].sum()) for c in STATS if c in b}
                x, o = np.stack(b["x"].to_numpy()), np.stack(b["outcomes"].to_numpy())
                outcomes = {h: o[:, j] for j, h in enumerate(policy.heads)}
                g, part = update_sums(policy, x, outcomes, *(b[c].to_numpy() for c in ("adv", "lp_old", "lp_ref")), eps, beta)
                total, value = total + g, value + part
                n += len(b)
        if n:
            yield pd.DataFrame({"i": [*range(total.size), -1, -2, *range(-3, -3 - len(told), -1)], "g": [*total.ravel(), value, float(n), *told.values()]})

    return run


#: The tags and the step mark of a response, as the column functions have them.
TAGS, STEP, ORDER, WHITE = ("<think>", "</think>", "<answer>", "</answer>"), "Step ([0-9]+):", "1,2,3,4,5,6", " \t\n\r"


def text_rewards(text: str, labels, threshold: int, max_tokens: int) -> tuple[float, float, str]:
    """(format reward, length reward, answer) of one response: what the column functions say, for a task that holds texts in memory."""
    import re

    think, think_end, said, said_end = TAGS
    tokens = text.split(" ")
    text = " ".join(tokens[:max_tokens]) if len(tokens) > max_tokens else text
    t = text.strip(WHITE)

    def block(opening, closing):
        there = t.count(opening) == 1 and t.count(closing) == 1 and t.index(opening) < t.index(closing)
        return there, t.split(closing)[0].split(opening)[-1] if there else ""

    (thought, steps), (answered, answer) = block(think, think_end), block(said, said_end)
    answer = answer.strip(WHITE)
    gap = t.split(said)[0].split(think_end)[-1]
    laid = t.startswith(think) and t.endswith(said_end) and not gap.strip(WHITE) and not re.split("Step [0-9]+:", steps)[0].strip(WHITE)
    good = thought and answered and laid and ",".join(re.findall(STEP, steps)) == ORDER and answer in labels
    return float(good), float(len(text) > threshold), answer


def rl_chain(policy: Policy, ref: Policy, rl, labels, lr_of, seed: str):
    """Rows in the order of their step -> the weights after all steps (step -1), and what each step's responses earned, as (step, i, g) rows.

    A step's responses are sampled, scored on their texts, set against their group and climbed on ``mu`` times, as in
    the form that makes jobs of a step; the task holds one step's rows. ``rl`` is the configuration of the stage, and
    ``lr_of`` gives a step's learning rate. A response's text follows from its outcomes, so each text is scored once.
    """

    def run(batches):
        import pandas as pd

        own, earned, out, held = policy.copy(), {}, [], None

        def step(rows):
            s, n = int(rows["step"].iloc[0]), len(rows) * rl.k
            x = np.repeat(np.stack(rows["x"].to_numpy()), rl.k, axis=0)
            keys = [f"{seed}:{s}:{i}:{j}" for i in rows["sample_id"] for j in range(rl.k)]
            taken, lp_old = own.steps(x, sampler(rl.temperature, uniforms_of(keys, own.heads) if rl.temperature else {}))
            lp_ref = ref.replay(x, {h: np.maximum(v, 0) for h, v in taken.items()})
            marks = []
            for j, key in enumerate(zip(*(v.tolist() for v in taken.values()), strict=True)):
                if key not in earned:
                    earned[key] = text_rewards(render(own, taken, j), labels, rl.length_threshold, rl.max_tokens)
                marks.append(earned[key])
            gold = np.repeat(rows["gold"].to_numpy(), rl.k)
            r = np.array([(f, size, float(answer == g)) for (f, size, answer), g in zip(marks, gold, strict=True)])
            reward = r @ np.array(rl.reward_weights)
            groups = reward.reshape(-1, rl.k)
            spread = groups.std(axis=1, ddof=rl.ddof, keepdims=True) if rl.k > rl.ddof else np.zeros((len(groups), 1))
            flat = spread <= 1e-12
            adv = np.where(flat, 0.0, (groups - groups.mean(axis=1, keepdims=True)) / np.where(flat, 1.0, spread)).ravel()
            for k in range(rl.mu):
                g, value = update_sums(own, x, taken, adv, lp_old, lp_ref, rl.eps, rl.beta)
                if not k:
                    out.extend((s, i, float(v)) for i, v in enumerate([n, value / n, *r.mean(axis=0), reward.mean(), rows["easy"].sum()]))
                own.theta += lr_of(s) * g / n

        for b in batches:
            held = b if held is None else pd.concat([held, b], ignore_index=True)
            ends = np.flatnonzero(np.diff(held["step"].to_numpy())) + 1  # steps that are there in full
            at = 0
            for end in ends:
                step(held.iloc[at:end])
                at = end
            held = held.iloc[at:].reset_index(drop=True)
        if held is not None and len(held):
            step(held)
        if out:
            out += [(-1, i, float(v)) for i, v in enumerate(own.theta.ravel())]
            yield pd.DataFrame(out, columns=["step", "i", "g"])

    return run
