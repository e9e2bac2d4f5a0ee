"""Relational operators around the methods: frames in, frames out."""
