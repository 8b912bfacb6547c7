"""Every global name that the package's functions use exists: a missing import shows only when its query runs."""

import builtins
import dis
import importlib
import pkgutil
import types

import densesql


def loaded(code):
    """Names that a code object, or one nested in it, reads as globals."""
    for i in dis.get_instructions(code):
        if i.opname == "LOAD_GLOBAL":
            yield i.argval
    for inner in code.co_consts:
        if isinstance(inner, types.CodeType):
            yield from loaded(inner)


def functions(module):
    for value in list(vars(module).values()):
        if isinstance(value, types.FunctionType) and value.__module__ == module.__name__:
            yield value
        elif isinstance(value, type) and value.__module__ == module.__name__:
            yield from (f for f in vars(value).values() if isinstance(f, types.FunctionType))


def test_no_function_uses_an_undefined_name():
    missing = set()
    for found in pkgutil.walk_packages(densesql.__path__, "densesql."):
        module = importlib.import_module(found.name)
        for f in functions(module):
            missing |= {(found.name, f.__name__, n) for n in loaded(f.__code__) if n not in f.__globals__ and not hasattr(builtins, n)}
    assert not missing
