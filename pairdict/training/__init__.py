from .train import TrainStats, adaptive_threshold, adaptive_threshold_col, suggest_bits, train, train_by, train_sharded, train_thresholds, train_widths

__all__ = ["TrainStats", "adaptive_threshold", "adaptive_threshold_col", "suggest_bits", "train", "train_by", "train_sharded", "train_thresholds", "train_widths"]
