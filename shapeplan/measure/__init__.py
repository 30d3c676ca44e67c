"""Measures: answer traces, diefficiency, grounded rules, checks, retrieved entities."""
