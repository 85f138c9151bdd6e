"""Operator DAGs: recording, fusion, rewriting, lowering, selection, schedules."""
