"""What the supervised blocker optimises: (recall, pairs for each record, seconds) -> a comparable value, larger is better."""

from __future__ import annotations


def recall_target(target: float, c_rt: float = 0.01):
    """First reach the recall; then least pairs for each record and a hundredth of the seconds."""

    def value(recall: float, k_eff: float, seconds: float) -> tuple:
        return (1, -(k_eff + c_rt * seconds)) if recall >= target - 1e-12 else (0, recall)

    return value


def linear(c_k: float, c_rt: float = 0.01):
    return lambda recall, k_eff, seconds: recall - c_k * k_eff - c_rt * seconds


def cost(k_eff: float, seconds: float, c_rt: float = 0.01) -> float:
    return k_eff + c_rt * seconds
