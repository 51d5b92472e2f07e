"""Readers and writers: text alignments, byte blocks, block-compressed files."""
