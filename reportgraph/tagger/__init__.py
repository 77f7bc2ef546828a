"""Sequence taggers: recurrent encoder, attention, conditional random field, one or two tasks."""
