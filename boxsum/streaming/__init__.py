"""Upkeep of anchor tables under appended, streamed and late cells."""
