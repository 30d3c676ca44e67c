"""The shape language: paths, value tests, constraints, shapes and schemas."""

from shapeplan.model.ast import And, Count, Not, Or, Shape, ShapeSchema, UnsupportedFragment, ValueTest
from shapeplan.model.parse import load_schema, schema_from_dict

__all__ = ["And", "Count", "Not", "Or", "Shape", "ShapeSchema", "UnsupportedFragment", "ValueTest", "load_schema", "schema_from_dict"]
