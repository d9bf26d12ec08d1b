"""Streaming views of the event edges."""
