from .base import BigramModel, LinearModel, LogisticModel, MlpModel, Model, SoftmaxModel, SparseEmbeddingModel

__all__ = ["BigramModel", "LinearModel", "LogisticModel", "MlpModel", "Model", "SoftmaxModel", "SparseEmbeddingModel"]
