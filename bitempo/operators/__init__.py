"""The thirteen operators. Each takes DataFrames that the belief pin has scoped already (see ``plans.registry``) and returns one."""
