"""Distributed operators over event logs."""
