"""Plug-ins, pools and the choice of plan."""
