"""Registered queries of the detector."""
