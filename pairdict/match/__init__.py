from .dynamic import DynamicMatcher
from .static import StaticIndex
from .vector import VectorIndex

__all__ = ["DynamicMatcher", "StaticIndex", "VectorIndex"]
