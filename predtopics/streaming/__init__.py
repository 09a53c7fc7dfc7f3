"""Structured streams of events and facts."""
