"""Stored frames that can answer a narrower model without another scan."""

from __future__ import annotations

from lincompress.operators.compress import CompressedFrame, rollup
from lincompress.plans.design import ModelSpec


class Registry:
    def __init__(self):
        self.frames: list[CompressedFrame] = []

    def add(self, cf: CompressedFrame) -> None:
        self.frames.append(cf)

    def find(self, spec: ModelSpec, segment=None, segment_keys: tuple[str, ...] = ()) -> CompressedFrame | None:
        """A frame that holds all features, outcomes, weights and segment columns, rolled up to the model's features."""
        for cf in sorted(self.frames, key=lambda f: len(f.keys)):
            s = cf.spec
            held = set(cf.keys)
            if cf.kind not in ("stats", "binary", "weighted", "within") or s.weight != spec.weight or not set(spec.outcomes) <= set(s.outcomes):
                continue
            if spec.cluster and cf.kind != "within" and spec.cluster not in held:
                continue
            if all(s.keys.get(k) == sql for k, sql in spec.keys.items()) and set(segment_keys) <= held:
                out = cf.where(segment) if segment is not None else cf
                if not spec.cluster and cf.kind != "within":
                    out = rollup(out, [k for k in cf.keys if k not in spec.keys])
                return CompressedFrame(out.df, cf.kind, spec, cf.extra)
        return None
