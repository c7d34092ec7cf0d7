"""Errors that policies, plans and enforcement raise."""


class PolicySyntaxError(ValueError):
    def __init__(self, message: str, pos: int = 0):
        super().__init__(f"{message} (at {pos})")
        self.pos = pos


class UnknownAttribute(ValueError):
    pass


class NonMonotonePlan(ValueError):
    def __init__(self, op: str):
        super().__init__(f"no agreed provenance for {op}")
        self.op = op


class UnsupportedPlan(ValueError):
    def __init__(self, strategy: str, op: str):
        super().__init__(f"{strategy} cannot rewrite {op}")
        self.strategy, self.op = strategy, op


class DimensionNotUnique(ValueError):
    pass


class ReservedName(ValueError):
    pass


class NonDeterministicPlan(ValueError):
    pass


class SchemaMismatch(ValueError):
    pass


class PolicyViolation(RuntimeError):
    def __init__(self, policy: str, count: int):
        super().__init__(f"{policy}: {count} violating rows")
        self.policy, self.count = policy, count


class ConcurrentWrite(RuntimeError):
    pass
