"""Cuts, blocks, storage forms, block lists, planner, block programs and their runtime."""
