"""Engines: naive, naive in Python workers, planned, fused; fixed points; bounded endpoints."""

from shapeplan.execute.engines import ValidationResult, validate

__all__ = ["ValidationResult", "validate"]
