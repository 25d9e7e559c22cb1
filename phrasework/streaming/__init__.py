"""Parses over Structured Streaming: closed windows, sessions, and an online left parse."""
