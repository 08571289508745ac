"""Spark-native scoring and selection of long documents by long-range dependency."""

from spanfocus.geometry import Geometry

__all__ = ["Geometry"]
__version__ = "0.1.0"
