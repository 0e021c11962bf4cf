"""Column expressions: relevance scores, the integer coin and text helpers."""

from .score import coin, gain, linear_score, ratio_score, weight_millionths

__all__ = ["coin", "gain", "linear_score", "ratio_score", "weight_millionths"]
