"""Schedules of mending rounds and experiment runners."""
