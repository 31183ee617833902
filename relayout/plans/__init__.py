"""Layouts, overlays, costs, graphs, gains, assignments: everything that is planned before data moves."""
