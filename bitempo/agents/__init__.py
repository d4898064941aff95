"""Stand-ins for the untrusted planner and reporter: scripted ones, and ones that err at given rates."""
