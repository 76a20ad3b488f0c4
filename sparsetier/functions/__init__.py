"""Closed-form storage costs, chunk plans and ideal volumes."""
