"""Streaming forms of profiles, drift alarms and matching."""
