"""Versioned tables with update logs, operator state and the sketch catalog."""
